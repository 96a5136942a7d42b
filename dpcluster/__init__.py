"""Clustering under a privacy budget, and operators around it, as DataFrame plans."""
