"""PySpark-native engine for large ensemble particle filters."""
