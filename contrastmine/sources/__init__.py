"""Readers, writers and the labelled workloads built from the given tables."""
