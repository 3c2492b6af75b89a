"""PySpark-native landmark manifold embedding."""
