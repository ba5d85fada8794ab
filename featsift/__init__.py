"""Information-theoretic feature selection on Spark DataFrames."""
