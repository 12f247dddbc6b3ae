"""hetpart: edge partitioning of large graphs for machines of unequal speed, memory and network cost."""

from __future__ import annotations


def partition(edges, fleet, method: str = "full", **options):
    """(src, dst, machine, seq) for edges (src, dst); options as in operators.partitioners.partition."""
    from .operators.partitioners import partition as run

    return run(edges, fleet, method, **options)


def evaluate(assignment, fleet):
    """Cost of each machine for an assignment (src, dst, machine)."""
    from .operators.costs import costs

    return costs(assignment, fleet)
