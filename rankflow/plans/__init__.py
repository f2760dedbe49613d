"""Workloads, fault simulation, oracles and the registry of queries."""
