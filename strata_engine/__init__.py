"""Low-noise comparison of two large populations of feature vectors, on Spark."""
