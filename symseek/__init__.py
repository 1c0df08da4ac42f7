"""Online approximate matching over symbol streams, on Spark DataFrames."""
