"""Readers, writers and a generator source."""
