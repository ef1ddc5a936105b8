"""Sparse two-sided interaction analytics on Spark: neighbour search, blended low-rank models, online updates."""
