"""Digests of streams."""
