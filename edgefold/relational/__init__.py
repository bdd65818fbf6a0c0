"""Relational queries around the graph methods: building edges, feeding programs, summarising results."""
