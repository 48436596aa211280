"""Set-based operators: graphs, partitions, sampling, exchange, caches and layers."""
