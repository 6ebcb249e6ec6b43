"""Incremental and windowed pattern counts over streams of edges."""
