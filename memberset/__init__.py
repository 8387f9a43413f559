"""memberset: approximate-membership filters of the Bloom family as Spark DataFrames."""
