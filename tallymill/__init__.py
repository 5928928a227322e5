"""Sketched count statistics for Bayesian samplers on Spark."""
