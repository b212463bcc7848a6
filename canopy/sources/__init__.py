"""Encoders from tables to forests."""
