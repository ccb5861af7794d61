"""A Spark-native engine for finding all occurrences of small patterns in very large graphs."""
