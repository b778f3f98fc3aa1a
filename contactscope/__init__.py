"""Contact-exposure analytics on Spark: segments, exposure rates, space-time index, pruning and joins."""
