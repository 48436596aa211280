"""Numeric kernels: layers with hand-derived gradients, losses, optimisers and parameters, in NumPy."""
