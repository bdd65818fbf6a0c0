"""Comparators: split-phase engines, stored messages, mirrors, map/reduce rounds, matrices, RDDs."""
