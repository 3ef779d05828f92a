"""Even-density partition clustering on Spark DataFrames."""
