"""Graph-partitioned message passing on Spark."""
