"""Graph algorithms over cells, plain or decoded from a compressed form; results do not depend on the codec."""
