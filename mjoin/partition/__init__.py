"""Cubes of relations, curves through their cells, and the regions cut from them."""
