"""Tables, test series and the Python data source of thinned series."""
