"""groupmatch: fuzzy group matching in attributed social graphs, on Spark DataFrames."""
