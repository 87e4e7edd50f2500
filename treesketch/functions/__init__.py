"""Expressions and scalar formulas: hashing, fixed point, costs."""
