"""Brute force over small graphs: what every method is held against."""




def adjacency(edges):
    out = {}
    for s, d, label in edges:
        out[s, d] = out[d, s] = label
    return out


def matches(q, vlabels, edges, semantics="iso"):
    """All maps of a pattern into a labelled graph given as {vertex: label} and (src, dst, label) edges."""
    have = adjacency(edges)
    fit = [[v for v, label in vlabels.items() if q.vlabels[u] in (None, label)] for u in range(q.n)]
    found = set()

    def grow(m):
        u = len(m)
        if u == q.n:
            found.add(tuple(m))
            return
        for v in fit[u]:
            if semantics == "iso" and v in m:
                continue
            if all((m[a], v) in have and label in (None, have[m[a], v]) for a, b, label in q.edges if b == u):
                grow([*m, v])

    grow([])
    return found


def candidates(q, shape, vlabels, edges, top_down=True):
    """(up, down) sets by definition over a rooted tree or DAG."""
    have = adjacency(edges)
    fits = lambda p, c, v, w: (v, w) in have and q.edges[q.edge_between(p, c)][2] in (None, have[v, w])
    labelled = {u: {v for v, label in vlabels.items() if q.vlabels[u] in (None, label)} for u in range(q.n)}
    up, down = {}, {}
    for u in shape.order:
        up[u] = {v for v in labelled[u] if not top_down or all(any(fits(p, u, w, v) for w in up[p]) for p in shape.parents[u])}
    for u in reversed(shape.order):
        down[u] = {v for v in up[u] if all(any(fits(u, c, v, w) for w in down[c]) for c in shape.children[u])}
    return up, down


