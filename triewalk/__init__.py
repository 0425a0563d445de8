"""triewalk: worst-case-optimal multiway joins and their cost theory on Spark DataFrames."""
