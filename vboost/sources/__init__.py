"""Workloads on the given tables, sources and sinks."""
