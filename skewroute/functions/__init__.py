"""Scalar functions: key hashing, bounds and the choice of the number of candidates."""
