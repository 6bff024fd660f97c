"""fragsim: a Spark-native engine that finds similar fragments in very large collections."""

__version__ = "0.1.0"
