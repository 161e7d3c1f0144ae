"""Masks, searches, reductions, costs: what is decided before rows are touched."""
