"""Segmentation cross-comparison on Spark: exact polygon overlap, Jaccard scores and their cost measures."""
