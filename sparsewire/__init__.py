"""Compression of sparse tensors as DataFrames: index codecs, value codecs, measures, workloads."""
