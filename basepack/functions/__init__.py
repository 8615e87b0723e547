"""Catalyst expressions and numeric kernels."""
