"""A Spark-native engine for web gathering and the analysis of web graphs."""
