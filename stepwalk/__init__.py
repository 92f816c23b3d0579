"""Second-order biased random walks on large graphs, on Spark."""
