"""A pattern: a small connected labelled graph held by the driver."""

from __future__ import annotations

import json
from collections import deque
from dataclasses import dataclass
from itertools import permutations


class UnsupportedPattern(ValueError):
    """The method does not take patterns of this shape."""


class UnsupportedUpdate(ValueError):
    """The method does not take updates of this kind."""


@dataclass(frozen=True)
class Pattern:
    """vlabels[i] is the label of vertex i, edges are (u, w, label) with u < w; a label of None fits all."""

    vlabels: tuple[str | None, ...]
    edges: tuple[tuple[int, int, str | None], ...]
    name: str = ""

    def __post_init__(self):
        seen = set()
        for u, w, _ in self.edges:
            if not 0 <= u < w < len(self.vlabels) or (u, w) in seen:
                raise ValueError(f"bad pattern edge {(u, w)}")
            seen.add((u, w))
        if len(self.vlabels) < 2 or len(self.reach(0)) < len(self.vlabels):
            raise ValueError("a pattern has two or more vertices and is connected")

    @property
    def n(self) -> int:
        return len(self.vlabels)

    @property
    def m(self) -> int:
        return len(self.edges)

    def neighbours(self, u: int) -> list[int]:
        return sorted({b for a, b, _ in self.edges if a == u} | {a for a, b, _ in self.edges if b == u})

    def degree(self, u: int) -> int:
        return len(self.neighbours(u))

    def edge_between(self, u: int, w: int) -> int | None:
        """Number of the edge between two vertices, if there is one."""
        return next((i for i, e in enumerate(self.edges) if {e[0], e[1]} == {u, w}), None)

    def reach(self, start: int) -> dict[int, int]:
        """Hops from a vertex."""
        hops, queue = {start: 0}, deque([start])
        while queue:
            u = queue.popleft()
            for w in self.neighbours(u):
                if w not in hops:
                    hops[w] = hops[u] + 1
                    queue.append(w)
        return hops

    @property
    def diameter(self) -> int:
        return max(max(self.reach(u).values()) for u in range(self.n))

    @property
    def is_tree(self) -> bool:
        return self.m == self.n - 1

    @property
    def density_class(self) -> str:
        """tree, sparse (average degree up to 3) or dense."""
        return "tree" if self.is_tree else "sparse" if 2 * self.m <= 3 * self.n else "dense"

    def automorphisms(self) -> int:
        """Label-preserving maps of the pattern onto itself."""
        have = {(u, w): label for u, w, label in self.edges} | {(w, u): label for u, w, label in self.edges}
        return sum(
            all(self.vlabels[p[i]] == self.vlabels[i] for i in range(self.n)) and all(have.get((p[u], p[w]), "\0") == label for u, w, label in self.edges)
            for p in permutations(range(self.n))
        )

    def to_json(self) -> str:
        return json.dumps({"name": self.name, "vlabels": self.vlabels, "edges": self.edges})

    def to_df(self, spark):
        return spark.createDataFrame([(self.name, list(self.vlabels), [tuple(e) for e in self.edges])], "pid string, vlabels array<string>, edges array<struct<u:int,w:int,elabel:string>>")


def parse(text: str, vlabels, elabels=None, name: str = "") -> Pattern:
    """Pattern from an edge list such as ``01 12 02``; elabels is one label, a list in edge order, or None for all."""
    pairs = [tuple(sorted((int(p[0]), int(p[1])))) for p in text.split()]
    labels = list(elabels) if isinstance(elabels, (list, tuple)) else [elabels] * len(pairs)
    return Pattern(tuple(vlabels), tuple((u, w, label) for (u, w), label in zip(pairs, labels, strict=True)), name)


def from_json(text: str) -> Pattern:
    x = json.loads(text)
    return Pattern(tuple(x["vlabels"]), tuple((u, w, label) for u, w, label in x["edges"]), x.get("name", ""))
