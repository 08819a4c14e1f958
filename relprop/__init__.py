"""Column prediction over whole relational databases, on Spark DataFrames."""
