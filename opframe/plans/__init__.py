"""Formulas: operation timelines as query plans."""
