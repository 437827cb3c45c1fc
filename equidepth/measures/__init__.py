"""Checks, measures and experiment runners."""
