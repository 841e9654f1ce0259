"""Readers that turn tables into matrices."""
