"""Near-duplicate vectors by NN-descent.

A neighbour graph starts from random hyperplane cells and is refined by joining the neighbours of a vector with each
other: every round each vector gathers its neighbours, forward and backward, compares them pairwise in one matrix
product, and proposes the pairs that improve a list.  Rounds go on while lists change and until an audit of a bounded
set of vectors against all rows, in blocks, finds the wanted recall.  Edges at or over the threshold, checked in
double precision, are the links; components follow from them.

A list that is full of links is saturated: its vector may have more links than the list holds, and nearer ones hide
them.  Every saturated vector is compared with all rows, in bounded parts; only pairs of components that a link joins
leave a task.  A pair that a list drops in some round leaves a saturated list behind, so it is met again there.  If the
audit stays below the wanted recall after the last round, all vectors are compared with all rows.  The members of each
component then meet in pairs of blocks of fixed size, and only counts leave a block pair, so a group of thousands of
near copies costs comparisons but no listed pairs.  Equal vectors are one vector with a multiplicity.

Defined results: vectors that are null, empty or zero or hold a null or non-finite component link with nothing, as
do vectors of different lengths with each other; a row without vec_id links with nothing, has a null component and is
not kept; repeated rows count as vectors of their own; an empty table gives no row; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdelta.llm.common import dropped, ready, saved, table
from graphdelta.llm.components import components

THRESHOLD = 0.95
NEIGHBOURS, BACKWARD = 8, 8
TABLES, CELL, MOST_ROUNDS = 8, 96, 6
#: Vectors of the audit, the recall it asks for, and rows compared at once.
AUDITED, RECALL, BLOCK = 200, 0.98, 512
#: Vectors of a component that meet as many others in one task.
SHIPPED = 4096
STILL = 0.02
#: Numbers in the vectors that travel to the tasks at once, and what single precision may be off by.
TRAVEL, SLACK = 1 << 20, 1e-4


def matrix(column: pd.Series, kind=np.float64) -> np.ndarray:
    return np.array(column.tolist(), dtype=kind)


def unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def reach(x: np.ndarray, y: np.ndarray, threshold: float) -> np.ndarray:
    """Which rows of x and y reach the threshold: by matrix product, pairs too near to tell by ``cosines``."""
    s = x @ y.T
    near = s >= threshold
    i, j = np.nonzero(np.abs(s - threshold) < 1e-12 * (1 + x.shape[1]))
    if len(i):
        near[i, j] = cosines(x[i], y[j]) >= threshold
    return near


def cosines(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Cosine of each row of x with the same row of y, both of length one; the same in either order."""
    return np.einsum("ij,ij->i", x, y)


def can_link():
    """Whether a row (id, v) can link; never null."""
    v = F.col("v")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists(v, lambda x: x != 0)
    return F.col("id").isNotNull() & v.isNotNull() & F.coalesce(fine, F.lit(False))


def cells(reps: DataFrame, size: int, count: int) -> DataFrame:
    """First edges: the nearest in a cell of each of several sets of random hyperplanes."""
    bits = int(np.clip(np.ceil(np.log2(max(count, 1) / (CELL / 2))), 0, 40))
    planes = [np.random.default_rng(t).normal(size=(size, max(bits, 1))) for t in range(TABLES)]
    power = 1 << np.arange(max(bits, 1), dtype=np.int64)

    def code(frames):
        for part in frames:
            x = unit(matrix(part["v"]))
            for t in range(TABLES):
                c = ((x @ planes[t] > 0) @ power) if bits else np.zeros(len(x), dtype=np.int64)
                yield pd.DataFrame({"t": np.int32(t), "code": c, "id": part["id"].to_numpy(), "u": list(x.astype(np.float32))})

    coded = reps.mapInPandas(code, "t int, code long, id long, u array<float>")
    # a crowded cell is dealt out by the id, so that no task holds more than a cell's worth
    sizes = coded.groupBy("t", "code").count().filter(F.col("count") > CELL)
    dealt = coded.join(sizes, ["t", "code"], "left").withColumn("deal", F.when(F.col("count").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("id", "t"), F.ceil(F.col("count") / CELL))))
    return in_runs(dealt.select(F.xxhash64("t", "code", "deal").alias("w"), "id", F.lit(-2.0).cast("float").alias("low"), "u"))


def in_runs(gathered: DataFrame) -> DataFrame:
    """Compare all vectors that share w; propose (a, b, cos) pairs that beat the lowest entry of a's list."""

    def work(frames):
        def one(ids, low, x):
            if len(ids) < 2:
                return None
            s = x @ x.T
            s[ids[:, None] == ids[None, :]] = -3
            k = min(NEIGHBOURS, len(ids) - 1)
            best = np.argpartition(-s, k - 1, axis=1)[:, :k]
            rows = np.repeat(np.arange(len(ids)), k)
            cols = best.ravel()
            cos = s[rows, cols]
            good = cos > low[rows]
            return ids[rows[good]], ids[cols[good]], cos[good]

        rest = None
        for part in frames:
            part = part if rest is None else pd.concat([rest, part], ignore_index=True)
            w = part["w"].to_numpy()
            starts = np.append(0, np.flatnonzero(np.diff(w)) + 1)
            yield from many(part, starts, np.append(starts[1:], starts[-1]), one)
            rest = part.iloc[starts[-1] :]
        if rest is not None and len(rest):
            yield from many(rest, np.array([0]), np.array([len(rest)]), one)

    def many(part, starts, ends, one):
        ids, low, x = part["id"].to_numpy(), part["low"].to_numpy(), None
        out = []
        if ends[-1] > starts[0]:
            x = matrix(part["u"].iloc[: ends[-1]], np.float32)
        for i, j in zip(starts, ends, strict=True):
            if j - i > 1 and (got := one(ids[i:j], low[i:j], x[i:j])) is not None:
                out.append(got)
        if out:
            yield pd.DataFrame({"a": np.concatenate([o[0] for o in out]), "b": np.concatenate([o[1] for o in out]), "cos": np.concatenate([o[2] for o in out])})

    spread = gathered.repartition("w").sortWithinPartitions("w")
    return spread.mapInPandas(work, "a long, b long, cos float")


def best_of(edges: DataFrame) -> DataFrame:
    """The lists: NEIGHBOURS nearest of every vector."""
    order = Window.partitionBy("a").orderBy(F.desc("cos"), "b")
    return edges.groupBy("a", "b").agg(F.max("cos").alias("cos")).withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= NEIGHBOURS).drop("rank")


def descend(units: DataFrame, lists: DataFrame) -> DataFrame:
    """One round: each vector's neighbours meet, forward and a hashed few backward."""
    few = Window.partitionBy("b").orderBy(F.xxhash64("a", "b"), "a")
    back = lists.withColumn("n", F.row_number().over(few)).filter(F.col("n") <= BACKWARD).select(F.col("b").alias("w"), F.col("a").alias("id"))
    own = lists.select(F.col("a").alias("w"), F.col("b").alias("id"))
    low = lists.groupBy("a").agg(F.when(F.count(F.lit(1)) >= NEIGHBOURS, F.min("cos")).otherwise(F.lit(-2.0)).alias("low")).select(F.col("a").alias("id"), F.col("low").cast("float").alias("low"))
    with_low = units.join(low, "id", "left").select("id", F.coalesce("low", F.lit(-2.0).cast("float")).alias("low"), "u")
    met = own.unionByName(back).unionByName(units.select(F.col("id").alias("w"), "id")).distinct().join(with_low, "id").select("w", "id", "low", "u")
    return best_of(lists.unionByName(in_runs(met)))


def audit(units: DataFrame, links: DataFrame, threshold: float = THRESHOLD, most: int = AUDITED) -> float:
    """Share of the linked partners of a bounded set of vectors that lie in their component, against all rows."""
    some = units.orderBy(F.xxhash64("id", F.lit(3)), "id").limit(most).toPandas()
    if not len(some):
        return 1.0
    ids, x = some["id"].to_numpy(), matrix(some["u"], np.float32)

    def work(frames):
        for part in frames:
            for at in range(0, len(part), BLOCK):
                s = matrix(part["u"].iloc[at : at + BLOCK], np.float32) @ x.T
                i, j = np.nonzero(s >= threshold + 1e-5)
                found = part["id"].to_numpy()[at + i]
                yield pd.DataFrame({"q": ids[j], "id": found})[ids[j] != found]

    true = units.mapInPandas(work, "q long, id long")
    comp = links.select(F.col("id"), F.col("component"))
    placed = true.join(comp, "id", "left").join(comp.select(F.col("id").alias("q"), F.col("component").alias("cq")), "q", "left")
    hit, total = placed.agg(F.coalesce(F.sum(F.when(F.col("component") == F.col("cq"), 1).otherwise(0)), F.lit(0)), F.count(F.lit(1))).first()
    return hit / total if total else 1.0


def exact(reps: DataFrame, lists: DataFrame, threshold: float) -> DataFrame:
    """Pairs of the lists whose cosine in double precision reaches the threshold."""
    near = lists.filter(F.col("cos") >= threshold - SLACK).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    two = near.join(reps.select(F.col("id").alias("a"), F.col("v").alias("va")), "a").join(reps.select(F.col("id").alias("b"), F.col("v").alias("vb")), "b")

    def work(frames):
        for part in frames:
            if len(part):
                yield part.loc[cosines(unit(matrix(part["va"])), unit(matrix(part["vb"]))) >= threshold, ["a", "b"]]

    return two.mapInPandas(work, "a long, b long")


def saturated(lists: DataFrame, threshold: float) -> DataFrame:
    """(id) of the vectors whose list is full of links."""
    held = lists.groupBy("a").agg(F.count(F.lit(1)).alias("n"), F.min("cos").alias("low"))
    return held.filter((F.col("n") >= NEIGHBOURS) & (F.col("low") >= threshold - SLACK)).select(F.col("a").alias("id"))


def widened(reps: DataFrame, size: int, some: DataFrame, comp: DataFrame, threshold: float) -> DataFrame:
    """(id, component) after every link of the vectors ``some`` (id), compared with all rows, has joined components."""
    spark = reps.sparkSession
    placed = saved(reps.select("id", "v").join(comp, "id", "left").select("id", "v", F.coalesce("component", "id").alias("component"), F.col("component").isNotNull().alias("linked")), "placed")
    asked = saved(placed.join(some, "id", "left_semi").select("id", "v", "component"), "asked")
    parts = -(-asked.count() // max(TRAVEL // size, BLOCK))
    pairs = []
    for k in range(parts):
        part = asked.filter(F.pmod(F.xxhash64("id"), F.lit(parts)) == k).select("v", "component").toPandas()
        if not len(part):
            continue
        shared = spark.sparkContext.broadcast((unit(matrix(part["v"])), part["component"].to_numpy()))

        def work(frames, shared=shared):
            x, own = shared.value
            flat = x.astype(np.float32).T
            for rows in frames:
                if not len(rows):
                    continue
                y, theirs = unit(matrix(rows["v"])), rows["component"].to_numpy()
                for at in range(0, len(y), BLOCK):
                    here = slice(at, at + BLOCK)
                    i, j = np.nonzero((y[here].astype(np.float32) @ flat >= threshold - SLACK) & (theirs[here][:, None] != own))
                    sure = cosines(y[at + i], x[j]) >= threshold
                    yield pd.DataFrame({"a": theirs[at + i[sure]], "b": own[j[sure]]}).drop_duplicates()

        pairs.append(saved(placed.select("v", "component").mapInPandas(work, "a long, b long").distinct(), "pairs"))
    if not pairs:
        return comp
    every = pairs[0]
    for p in pairs[1:]:
        every = every.unionByName(p)
    merged = components(every).select(F.col("id").alias("component"), F.col("component").alias("joined"))
    after = placed.join(merged, "component", "left").filter(F.col("linked") | F.col("joined").isNotNull())
    return saved(after.select("id", F.coalesce("joined", "component").alias("component")), "components")


def link_counts(reps: DataFrame, comp: DataFrame, threshold: float) -> DataFrame:
    """(id, n): other vectors linked directly, from block pairs within each component.

    A vector travels once for every ``SHIPPED`` members of its component; a task compares ``BLOCK`` rows at a time.
    """
    sizes = comp.groupBy("component").count().withColumn("blocks", F.ceil(F.col("count") / SHIPPED).cast("int"))
    placed = reps.join(comp, "id").join(sizes, "component").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    spread = placed.select("component", "id", "v", "m", "block", other).select("component", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "id", "v", "m")

    def work(key, part):
        x, block, m, ids = unit(matrix(part["v"])), part["block"].to_numpy(), part["m"].to_numpy(), part["id"].to_numpy()
        left, right = np.flatnonzero(block == key[1]), np.flatnonzero(block == key[2])
        n, alone = np.zeros(len(ids), dtype=np.int64), key[1] == key[2]
        for at in range(0, len(left), BLOCK):
            mine = left[at : at + BLOCK]
            near = reach(x[mine], x[right], threshold)
            if alone:
                near &= mine[:, None] != right
            else:
                n[right] += m[mine] @ near
            n[mine] += near @ m[right]
        return pd.DataFrame({"id": ids, "n": n})

    return spread.groupBy("component", "i", "j").applyInPandas(work, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def linked(reps: DataFrame, size: int, threshold: float) -> DataFrame:
    """(id, n, component) of the vectors of one length that have links."""
    count = reps.count()

    def scale(frames):
        for part in frames:
            if len(part):
                yield pd.DataFrame({"id": part["id"], "u": list(unit(matrix(part["v"])).astype(np.float32))})

    units = saved(reps.select("id", "v").mapInPandas(scale, "id long, u array<float>"), "units")
    lists = saved(best_of(cells(reps.select("id", "v"), size, count)), "lists")
    comp = None
    for turn in range(MOST_ROUNDS):
        after = saved(descend(units, lists), "lists")
        changed = after.select("a", "b").join(lists.select("a", "b"), ["a", "b"], "left_anti").count()
        dropped(lists)
        lists = after
        if turn and (changed <= STILL * NEIGHBOURS * max(count, 1) or turn == MOST_ROUNDS - 1 or turn % 2):
            comp = saved(components(exact(reps, lists, threshold)), "components")
            comp = widened(reps, size, saturated(lists, threshold), comp, threshold)
            if audit(units, comp, threshold) >= RECALL:
                break
    else:
        comp = widened(reps, size, units.select("id"), comp, threshold)
    return link_counts(reps, comp, threshold).join(comp, "id")


def near_copies(vectors: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row of ``vectors`` (vec_id, embedding)."""
    spark = vectors.sparkSession
    ready(spark)
    rows = vectors.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    reps = saved(rows.filter(can_link()).groupBy("v").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("m")).select(F.col("first").alias("id"), "v", "m"), "vectors")
    parts = []
    for r in reps.groupBy(F.size("v").alias("d")).count().filter(F.col("count") > 1).orderBy("d").collect():
        parts.append(linked(reps.filter(F.size("v") == r["d"]), r["d"], threshold))
    known = reps
    if parts:
        links = parts[0]
        for p in parts[1:]:
            links = links.unionByName(p)
        known = reps.join(links.select("id", "n", "component"), "id", "left")
    else:
        known = reps.withColumn("n", F.lit(0).cast("long")).withColumn("component", F.lit(None).cast("long"))
    of_vector = known.select("v", (F.coalesce("n", F.lit(0)) + F.col("m") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    fine = rows.filter(can_link()).join(of_vector, "v").select("id", "n_links", "component_id")
    # rows that cannot link stand for themselves
    odd = rows.filter(~can_link()).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return fine.unionByName(odd).select(F.col("id").alias("vec_id"), "n_links", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(False)).alias("kept"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
