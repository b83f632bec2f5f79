"""Similarity search over groups of vectors that one representative each stands for, on Spark."""
