"""Streaming twins of the workload builders and online placement."""
