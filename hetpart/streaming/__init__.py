"""Placement and measures over edge streams."""
