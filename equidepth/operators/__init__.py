"""Operators served from one sliced exchange."""
