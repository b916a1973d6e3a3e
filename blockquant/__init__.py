"""Block-wise lossy compression of noise-dominated samples on Spark."""
