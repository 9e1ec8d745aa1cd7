"""Spark-native engine for preparing, scoring and evaluating sentence-pair corpora."""
