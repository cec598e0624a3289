"""Detection of collective and point anomalies in many parallel series, on Spark."""
