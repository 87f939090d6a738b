"""Driver-side planning: the lattice, its chains, and the slots of the shuffle."""
