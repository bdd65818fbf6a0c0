"""Graph algorithms as programs over the super-step engine and as contraction loops."""
