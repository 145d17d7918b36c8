"""Portable hashing, exact cap arithmetic and shared-storage helpers."""
