"""Frozen pivots on streams, and load monitors."""
