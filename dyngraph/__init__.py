"""dyngraph: incremental learning on evolving, client-partitioned graphs, on Spark."""
