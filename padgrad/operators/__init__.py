"""Codes, moments, sharing, training, baselines, latency and measures."""
