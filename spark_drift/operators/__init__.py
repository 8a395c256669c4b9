"""Drift operators: distances, degrees, mixtures, detectors, views, ensembles."""
