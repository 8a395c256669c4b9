"""Structured streaming forms of the monitors."""
