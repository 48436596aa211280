"""Minibatch training of graph neural networks on partitioned graphs, planned in bulk on Spark."""
