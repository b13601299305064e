"""Pattern-constrained nearest-neighbour search as DataFrame plans."""
