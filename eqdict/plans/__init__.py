"""Numeric kernels that grouped operators call, and their drivers."""
