"""Tensor builders, readers and writers."""
