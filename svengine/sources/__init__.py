"""Circuits from tables, formulas and gate scripts."""
