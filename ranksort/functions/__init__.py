"""Scalar functions, and the SQL surface of the engine."""
