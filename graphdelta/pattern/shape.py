"""Rooted trees and DAGs over a pattern."""

from __future__ import annotations

from dataclasses import dataclass

from graphdelta.pattern.model import Pattern


@dataclass(frozen=True)
class Rooted:
    """An order of the vertices and, per vertex, the tree or DAG edges to earlier (parents) and later ones (children)."""

    root: int
    order: tuple[int, ...]
    parents: dict[int, tuple[int, ...]]
    children: dict[int, tuple[int, ...]]

    def edges(self) -> list[tuple[int, int]]:
        return [(p, u) for u in self.order for p in self.parents[u]]

    def path_up(self, u: int) -> list[int]:
        """Vertices from u to the root of a tree, both included."""
        out = [u]
        while self.parents[out[-1]]:
            out.append(self.parents[out[-1]][0])
        return out

    def height(self) -> int:
        longest = {u: 0 for u in self.order}
        for u in self.order:
            for p in self.parents[u]:
                longest[u] = max(longest[u], longest[p] + 1)
        return max(longest.values())


def _rooted(root: int, order: list[int], pairs: list[tuple[int, int]]) -> Rooted:
    parents = {u: tuple(sorted(p for p, c in pairs if c == u)) for u in order}
    return Rooted(root, tuple(order), parents, {u: tuple(sorted(c for p, c in pairs if p == u)) for u in order})


def spanning_tree(q: Pattern, edge_size: list[int], label_size: list[int]) -> Rooted:
    """Root at the rarer end of the rarest edge; grow by the rarest edge that leaves the tree; depth-first order."""
    first = min(range(q.m), key=lambda e: (edge_size[e], e))
    root = min(q.edges[first][:2], key=lambda u: (label_size[u], u))
    inside, pairs = {root}, []
    while len(inside) < q.n:
        out = [e for e in range(q.m) if (q.edges[e][0] in inside) != (q.edges[e][1] in inside)]
        u, w, _ = q.edges[min(out, key=lambda e: (edge_size[e], e))]
        pairs.append((u, w) if u in inside else (w, u))
        inside |= {u, w}
    return _rooted(root, depth_first(root, pairs), pairs)


def depth_first(root: int, pairs: list[tuple[int, int]]) -> list[int]:
    out, stack = [], [root]
    while stack:
        u = stack.pop()
        out.append(u)
        stack += sorted((c for p, c in pairs if p == u), reverse=True)
    return out


def rooted_tree(q: Pattern, root: int = 0) -> Rooted:
    """A tree pattern directed away from a root, in depth-first order."""
    pairs, seen, stack = [], {root}, [root]
    while stack:
        u = stack.pop()
        for w in q.neighbours(u):
            if w not in seen:
                seen.add(w)
                pairs.append((u, w))
                stack.append(w)
    return _rooted(root, depth_first(root, pairs), pairs)


def breadth_first(q: Pattern, root: int) -> list[int]:
    hops = q.reach(root)
    return list(hops)


def rooted_dag(q: Pattern) -> Rooted:
    """All edges directed by a breadth-first visit, from the root that gives the highest DAG."""
    best = None
    for root in range(q.n):
        order = breadth_first(q, root)
        place = {u: i for i, u in enumerate(order)}
        pairs = [(u, w) if place[u] < place[w] else (w, u) for u, w, _ in q.edges]
        dag = _rooted(root, order, pairs)
        if best is None or dag.height() > best.height():
            best = dag
    return best
