"""Communities in snapshot-based temporal graphs, on Spark DataFrames."""
