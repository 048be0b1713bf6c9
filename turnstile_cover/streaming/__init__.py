"""Sketch maintenance and windows over streams."""
