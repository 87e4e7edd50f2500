"""Tables, streams and synthetic gradients to read."""
