"""Index-backed detection of complex patterns in event logs, on Spark DataFrames."""
