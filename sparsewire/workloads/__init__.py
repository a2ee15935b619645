"""Experiments, training loops and the driver's queries."""
