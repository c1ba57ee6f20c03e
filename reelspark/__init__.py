"""A Spark-native engine for queries whose answer is a video."""
