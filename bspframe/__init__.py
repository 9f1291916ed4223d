"""PySpark-native engine for iterative graph analytics."""
