"""Streams of gradients."""
