"""Two-way phrase parsing of strings held in Spark DataFrames."""
