"""gnnspark: mini-batch training of graph neural networks on Spark tables."""
