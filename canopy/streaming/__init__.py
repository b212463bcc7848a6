"""Runs and day trees over an event stream."""
