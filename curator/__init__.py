"""Spark-native corpus curation: geometry-driven mixing, selection and measurement of training text."""
