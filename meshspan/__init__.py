"""Leading-subspace estimation over coordinator-free networks, on Spark DataFrames."""
