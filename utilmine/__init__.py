"""High-utility itemset mining with per-item thresholds, on Spark DataFrames."""
