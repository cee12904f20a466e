"""segraph: affinity-graph partitioning on Spark dataframes."""
