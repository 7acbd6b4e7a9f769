"""dpgrid: grid clustering of point sets under differential privacy, on Spark DataFrames."""
