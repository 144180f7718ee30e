"""PySpark-native engine that finds the events which move a numeric index."""
