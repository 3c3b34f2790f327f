"""Which index and which order to take for a pattern on a graph."""

from __future__ import annotations

from graphdelta.pattern.model import Pattern

SPARSE_DEGREE, SPARSE_CORE = 4.0, 10


def advise(q: Pattern, average_degree: float, long_running: bool = False, max_core: int | None = None) -> tuple[str, str]:
    """(index, order): the DAG's index for sparse or long-running patterns, else none; an order by shape and density."""
    kind = q.density_class
    thin = average_degree <= SPARSE_DEGREE or (max_core is not None and max_core <= SPARSE_CORE)
    index = "dag" if kind == "sparse" or long_running else "none"
    order = "bottomup" if kind == "tree" else "direct" if kind == "dense" or thin else "dag"
    return index, order
