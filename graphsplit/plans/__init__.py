"""Whole methods and what is measured on them."""
