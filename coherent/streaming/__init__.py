"""Drives and stateful propagation over event streams."""
