"""A Spark-native engine for full-graph, layer-by-layer inference of graph neural networks."""
