"""A Spark-native engine for outliers in numeric data streams."""
