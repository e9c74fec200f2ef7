"""rangecut: splitter search, balanced range partitioning and the operators built on them, for PySpark."""

__version__ = "0.1.0"
