"""A Spark-native engine for graph-based nearest-neighbour search over dense vectors."""

__version__ = "0.1.0"
