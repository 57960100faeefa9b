"""Windowed moments of streams and additive maintenance of buffers."""
