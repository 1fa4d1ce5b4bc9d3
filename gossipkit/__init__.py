"""Spark-native engine for sparse, compressed, decentralized training."""
