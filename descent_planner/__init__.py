"""Cost-planned gradient descent over Spark DataFrames."""
