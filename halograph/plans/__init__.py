"""Epoch plans, and training over them."""
