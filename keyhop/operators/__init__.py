"""Strategies over stores, counters, baselines and the surrounding relational operators."""
