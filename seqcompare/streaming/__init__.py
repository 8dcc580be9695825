"""Incremental and event-time forms of the statistics."""
