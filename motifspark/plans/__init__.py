"""Driver-side objects: process trees, their languages, the candidate lattice and seed closures."""
