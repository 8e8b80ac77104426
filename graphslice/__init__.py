"""One-pass streaming graph partitioning with run-length-compressed assignments, on Spark DataFrames."""
