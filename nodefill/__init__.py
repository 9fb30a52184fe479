"""Spark-native engine for variable-density node placement and spacing-controlled sampling."""
