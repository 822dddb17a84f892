"""Incremental marginals and grids of event streams."""
