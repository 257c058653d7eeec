"""Tiles, meshes, cuts, placement, the phases of a step, and measures."""
