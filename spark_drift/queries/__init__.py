"""Registered queries, grouped by subject, each with its SQL twin where there is one."""
