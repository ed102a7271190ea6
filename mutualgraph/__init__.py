"""Joint community detection over partially aligned networks, on Spark DataFrames."""
