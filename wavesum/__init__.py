"""Wavelet summaries of key distributions, as Spark plans."""
