"""Sketches, their algebra and release, decoders, baselines and measures."""
