"""Frames from a stream of shots."""
