"""Samplers and windowed counts over streams."""
