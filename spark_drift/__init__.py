"""Concept-drift analytics on Spark: mixtures, energy distance, views, adaptation."""
