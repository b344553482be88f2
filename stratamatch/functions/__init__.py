"""Column expressions: treatments, coarsening, distances."""
