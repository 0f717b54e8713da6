"""Private distinct counting over many data holders, on Spark DataFrames."""
