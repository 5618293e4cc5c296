"""Query-focused collective entity resolution on Spark DataFrames."""
