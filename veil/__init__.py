"""veil: a PySpark-native engine for private record linkage between two parties."""
