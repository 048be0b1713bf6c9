"""Turnstile coverage and fingerprinting on Spark: linear sketches as ordinary tables."""
