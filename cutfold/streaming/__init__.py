"""Graphs from event streams, and partitions that follow them."""
