"""Streams: arrival of edges, and the cache as a stateful operator."""
