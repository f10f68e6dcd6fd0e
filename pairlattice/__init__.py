"""One-pass size estimation of similarity joins on Spark DataFrames."""
