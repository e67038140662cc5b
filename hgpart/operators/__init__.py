"""Distributed operators on hypergraphs, partitions and graphs."""
