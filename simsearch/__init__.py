"""String similarity search that relaxes a query and diversifies its answer, on Spark DataFrames."""
