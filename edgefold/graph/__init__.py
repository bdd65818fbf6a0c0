"""Property graphs: model, ids, builders from the given tables, generators, readers and writers."""
