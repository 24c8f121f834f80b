"""Spark-native reading of relational storage files, and the operators around it."""
