"""Readers, writers and workload builders."""
