"""Data side of graph neural networks on graphs with hubs: partitioning, sampling, layouts and inference in Spark."""
