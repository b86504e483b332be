"""Level-synchronous search over grid-partitioned graphs, for Spark."""
