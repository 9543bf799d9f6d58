"""Hashing, field arithmetic, equation rows and closed forms."""
