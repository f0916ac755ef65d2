"""Spark-native engine for budgeted augmentation of training tables."""
