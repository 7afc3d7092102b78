"""Private frequency estimation and string discovery on Spark DataFrames."""
