"""Spark-native engine for finding near-duplicate text at corpus scale."""
