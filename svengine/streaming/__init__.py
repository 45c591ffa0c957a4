"""Gate feeds as streams."""
