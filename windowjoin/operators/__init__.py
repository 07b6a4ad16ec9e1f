"""Operators around and inside the window join."""
