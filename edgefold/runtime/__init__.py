"""Shared runtime services: scratch tables, checkpoints and run metrics."""
