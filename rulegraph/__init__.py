"""A Spark-native engine for rule graphs over temporal facts."""
