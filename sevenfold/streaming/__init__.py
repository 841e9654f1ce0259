"""Incremental products and windowed matrices on streams."""
