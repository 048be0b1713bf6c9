"""Sketches, samplers, selection methods, baselines and measures over DataFrames."""
