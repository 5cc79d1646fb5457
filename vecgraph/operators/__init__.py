"""Exact search, quantizers, graphs, walks and features."""
