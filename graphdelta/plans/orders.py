"""Matching orders: pure functions of a pattern and of label statistics."""

from __future__ import annotations

from graphdelta.pattern.model import Pattern
from graphdelta.pattern.shape import Rooted


def check_connected(q: Pattern, order: list[int]) -> list[int]:
    """The order itself, if each vertex but the first has an earlier neighbour; else products would arise."""
    if sorted(order) != list(range(q.n)) or any(not set(q.neighbours(u)) & set(order[:i]) for i, u in enumerate(order) if i):
        raise ValueError(f"{order} is no connected order of the pattern")
    return order


def any_connected(q: Pattern, start: int = 0) -> list[int]:
    """Lowest id among the vertices next to the ordered part."""
    out = [start]
    while len(out) < q.n:
        out.append(min(w for u in out for w in q.neighbours(u) if w not in out))
    return out


def order_direct(q: Pattern, seed: tuple[int, int]) -> list[int]:
    """Both ends of the seed, then the vertex with most ordered neighbours, of those the one of largest degree."""
    out = list(seed)
    while len(out) < q.n:
        rest = [u for u in range(q.n) if u not in out]
        out.append(max(rest, key=lambda u: (len(set(q.neighbours(u)) & set(out)), q.degree(u), -u)))
    return check_connected(q, out)


def order_edges(q: Pattern, size: list[int]) -> list[int]:
    """Edges from the smallest relation on, always touching what is chosen."""
    out = [min(range(q.m), key=lambda e: (size[e], e))]
    while len(out) < q.m:
        have = {v for e in out for v in q.edges[e][:2]}
        near = [e for e in range(q.m) if e not in out and have & set(q.edges[e][:2])]
        out.append(min(near, key=lambda e: (size[e], e)))
    return out


def order_paths(tree: Rooted, paths: dict[int, int], rule: str = "min") -> list[int]:
    """Strip the leaf with the least (or greatest) number of path matches until the root is left; reversed."""
    left, gone = set(tree.order), []
    pick = min if rule == "min" else max
    while len(left) > 1:
        leaves = [u for u in left if u != tree.root and not set(tree.children[u]) & left]
        leaf = pick(leaves, key=lambda u: (paths[u], u))
        gone.append(leaf)
        left.remove(leaf)
    return [tree.root, *reversed(gone)]


def order_tree_seeded(q: Pattern, tree: Rooted, order: list[int], seed: tuple[int, int]) -> list[int]:
    """The seed, the climb from its first vertex to the root, then the rest in the given order."""
    out = list(dict.fromkeys([*seed, *tree.path_up(seed[0]), *order]))
    fixed = out[:2]
    rest = out[2:]
    while rest:  # a climb may pass the seed's other end, so keep the order but never leave a gap
        u = next(u for u in rest if set(q.neighbours(u)) & set(fixed))
        fixed.append(u)
        rest.remove(u)
    return check_connected(q, fixed)


def order_static(q: Pattern, size: list[int]) -> list[int]:
    """Densest core first, then smallest relation to the ordered part."""
    core, left, k = {}, set(range(q.n)), 0
    while left:
        u = min(left, key=lambda v: (len(set(q.neighbours(v)) & left), v))
        k = max(k, len(set(q.neighbours(u)) & left))
        core[u] = k
        left.remove(u)
    first = max(range(q.n), key=lambda u: (core[u], q.degree(u), -u))
    out = [first]
    while len(out) < q.n:
        near = [u for u in range(q.n) if u not in out and set(q.neighbours(u)) & set(out)]
        grow = lambda u: min(size[q.edge_between(u, w)] for w in q.neighbours(u) if w in out)
        out.append(min(near, key=lambda u: (-core[u], -len(set(q.neighbours(u)) & set(out)), grow(u), u)))
    return check_connected(q, out)


def seeded(q: Pattern, order: list[int], seed: tuple[int, int]) -> list[int]:
    """Any order moved to start at a seed edge, otherwise kept as far as it stays connected."""
    out, rest = list(seed), [u for u in order if u not in seed]
    while rest:
        u = next(u for u in rest if set(q.neighbours(u)) & set(out))
        out.append(u)
        rest.remove(u)
    return out
