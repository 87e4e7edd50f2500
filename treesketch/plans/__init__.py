"""Whole steps composed of operators, and checks of their physical plans."""
