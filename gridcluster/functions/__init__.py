"""Column functions: vectors, portable random numbers, features, layout of points."""
