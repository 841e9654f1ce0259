"""Schemes, layouts, cost formulas and planning; no jobs run here."""
