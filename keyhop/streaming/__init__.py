"""Keyed stores fed by streams."""
