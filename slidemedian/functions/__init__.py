"""Kernels and codes that run inside a task."""
