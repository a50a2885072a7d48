"""Column functions: portable random numbers, vectors, losses, and the SQL surface."""
