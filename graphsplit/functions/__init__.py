"""Formulas and hashes, as plain functions and as columns."""
