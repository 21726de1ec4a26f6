"""Label propagation with learned class compatibilities on Spark DataFrames."""
