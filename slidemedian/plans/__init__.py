"""Specifications, positions, tiles and routes."""
