"""A Spark-native engine for graphs with valid time and transaction time."""
