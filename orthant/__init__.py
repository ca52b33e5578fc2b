"""A Spark-native engine for exact nearest-neighbour search over partitioned point sets."""
