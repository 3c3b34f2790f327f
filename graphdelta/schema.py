"""Column layouts shared by the engine.

vertices (vid, vlabel), edges (src, dst, elabel, ts) with src < dst and one row a pair, arcs (src, dst, elabel,
slabel, dlabel): both directions of every edge with the labels of its ends, so that a query relation is a filter.
"""

VERTICES = "vid long, vlabel string"
EDGES = "src long, dst long, elabel string, ts timestamp"
ARCS = "src long, dst long, elabel string, slabel string, dlabel string"
UPDATES = "batch_id long, seq long, op string, src long, dst long, elabel string, ts timestamp"
ARC_COLUMNS = ["src", "dst", "elabel", "slabel", "dlabel"]
