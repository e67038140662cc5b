"""Kernels that run inside tasks, and functions for SQL."""
