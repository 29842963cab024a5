"""gridtide: Spark-native adaptive load balancing for spatial streams."""

__version__ = "0.1.0"
