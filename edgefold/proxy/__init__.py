"""The proxy graph: homes, single-direction stand-ins, local numbering and execution over it."""
