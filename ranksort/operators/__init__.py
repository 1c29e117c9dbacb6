"""Relational operators that use sorted, ranked relations."""
