"""Column functions: random numbers from keys, and small linear algebra on arrays."""
