"""Workloads, their SQL twins, and the linking pipeline."""
