"""Workloads, their SQL twins and recovery points."""
