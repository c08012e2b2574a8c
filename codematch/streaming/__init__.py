"""Continuous encoding, near-duplicate suppression and windows over streams."""
