"""Readers, planning, measures and workloads on top of the operators."""
