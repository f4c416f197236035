"""Arrivals of device answers as a stream."""
