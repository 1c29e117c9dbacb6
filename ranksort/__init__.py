"""Distributed Quicksort methods and order analytics on Spark DataFrames."""
