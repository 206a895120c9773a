"""Very large topic models over short texts, on Spark DataFrames."""
