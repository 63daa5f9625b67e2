"""Readers and workload definitions."""
