"""Relational operators, codecs and baselines."""
