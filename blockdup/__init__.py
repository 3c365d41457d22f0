"""blockdup: near-duplicate block detection on Spark DataFrames."""
