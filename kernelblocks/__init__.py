"""Randomized-kernel learning on Spark: block-split solver, feature maps, baselines and measures."""
