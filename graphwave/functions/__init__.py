"""Codecs and column functions."""
