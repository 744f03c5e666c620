"""Predicates, region tests and cell arithmetic as Column functions."""
