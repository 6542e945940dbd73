"""pinflow: one-pass hypergraph and graph partitioning on Spark."""
