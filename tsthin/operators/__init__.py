"""DataFrame operators: statistics, thinning, baselines, measures, forecasting and anomalies."""
