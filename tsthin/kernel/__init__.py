"""NumPy kernels that run inside Spark tasks; no Spark imports here."""
