"""Codec composition, the container, the planner and the network model."""
