"""Incremental counts from a stream of log rows."""
