"""Products, baselines and element-wise operators over matrices."""
