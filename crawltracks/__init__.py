"""A Spark-native engine that mines annotated outdoor tracks from a web crawl."""
