"""Loss-tolerant sketched matrix products, sketched optimisation and the relational operators around them, on Spark DataFrames."""
