"""Choices between physical ways to build a sketch, and the relational queries of the catalogue."""
