"""bandspark: bandwidth-reducing vertex ordering of large sparse graphs on Spark DataFrames."""
