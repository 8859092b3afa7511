"""A Spark-native engine for field and graph segmentation by pointer doubling."""
