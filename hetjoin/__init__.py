"""One-round evaluation of multiway joins on machines of unequal cost, on Spark DataFrames."""
