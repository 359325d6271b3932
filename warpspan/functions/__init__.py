"""Distances, envelopes and bounds: numpy kernels over batches and Spark expressions."""
