"""Relational operators of the engine: segmentation, exposure, pruning, store, leaves, comparators."""
