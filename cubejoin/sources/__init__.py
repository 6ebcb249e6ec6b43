"""Readers, generators, block stores and sinks."""
