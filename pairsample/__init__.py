"""Associated item pairs by biased pair sampling, on Spark DataFrames."""
