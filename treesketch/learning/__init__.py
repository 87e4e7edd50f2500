"""Gradients, schedules and the training loop."""
