"""Additively homomorphic backends."""
