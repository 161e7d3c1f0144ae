"""Bit functions, codecs and key layouts."""
