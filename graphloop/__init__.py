"""Loop-capable graph queries and iterative graph analytics on Spark DataFrames."""
