"""Readers, generated inputs and sinks."""
