"""Sparsifiers, index codecs, value codecs, policies, baselines and measures."""
