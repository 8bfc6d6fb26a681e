"""Progressive order-free coding of point sets on Spark: count trees, entropy coding, prediction, baselines."""
