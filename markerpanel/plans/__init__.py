"""Plan builders: presence, lattice, evidence, multiple testing, plan checks."""
