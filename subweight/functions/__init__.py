"""Column functions: ranks, random numbers from hashes, numeric solvers."""
