"""Digest-driven synchronisation of replicated state on Spark."""
