"""The write path: segments from a stream of changes."""
