"""Partitioning operators: costs, capacities, growth, local search, baselines, workloads."""
