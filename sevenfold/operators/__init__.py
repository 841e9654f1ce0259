"""Distributed operators on matrices kept as DataFrames."""
