"""evenbox: Spark-native spatial partitioning, indexing and querying."""
