"""A PySpark-native engine for fast distributed matrix multiplication."""
