"""Readers, writers and workload generators."""
