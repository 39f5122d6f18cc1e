"""Spark-native record blocking: rules, sketches, clustering, pairs, measures."""
