"""Streams: events in time windows, and graphs that grow."""
