"""Factorisations, products and measures."""
