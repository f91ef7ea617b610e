"""Moments and bags kept up to date over streams."""
