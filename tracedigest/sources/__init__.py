"""Readers and writers of payloads."""
