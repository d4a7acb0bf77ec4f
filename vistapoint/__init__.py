"""A Spark-native engine that finds the top-k points of interest in geotagged visual content."""
