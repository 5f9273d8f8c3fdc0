"""Description-length mining of box patterns in numeric tables, on Spark DataFrames."""
