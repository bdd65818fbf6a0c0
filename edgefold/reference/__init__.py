"""Plain single-machine versions, for tests only."""
