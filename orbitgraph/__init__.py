"""Spark-native engine for large periodic atomic graphs: neighbour graphs, partitioning, exchange, message passing."""
