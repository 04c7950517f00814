"""Spark-native learning of tracking-script detectors from API access traces."""
