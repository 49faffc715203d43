"""Spark-native release of microdata under per-value confidence-gain bounds."""
