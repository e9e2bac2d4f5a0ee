"""Ordered streams, external sorting and the blocking kinds."""
