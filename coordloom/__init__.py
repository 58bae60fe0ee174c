"""GLM training on Spark DataFrames; see README.md."""
