"""Cell-level cleaning benchmark engine on Spark DataFrames."""
