"""Order-free id compression for vector-search indexes, written for Spark."""
