"""Readers, tensor builders, planted data, and stored cuts of a plan."""
