"""Sampled graph neural networks on Spark: graph storage, sampling, forward passes, training order and tuning."""
