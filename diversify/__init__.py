"""Diverse subsets of very large point collections."""
