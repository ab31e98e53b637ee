"""Whole plans: digests kept on disk, experiment workloads, the query registry and its oracle SQL."""
