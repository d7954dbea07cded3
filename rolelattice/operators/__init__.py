"""Blocks, lattice, search and measures over them."""
