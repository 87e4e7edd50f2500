"""Relational operators: sketches, trees, recovery, compression, measures."""
