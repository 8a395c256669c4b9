"""A stable two-dimensional map of old and new rows, and the tables around it."""
