"""Exact n-gram Jaccard join with adaptive multi-match prefixes.

A text is the set of hashes of its word n-grams, ordered by hash.  Two sets of similarity t or more share at least k of
the first ``n - ceil(t n) + k`` members, for every k; so a document may lengthen its prefix and ask for more shared
members in turn.  Each document takes the length under which the members to be shared exceed the frequent ones in the
prefix by most: so many shared members are rare, only the short lists of rare members are looked at, and a pair
that shares fewer of them is not verified.  A document whose members are
frequent nearly throughout (one of a large group of near copies) is wide: its prefix is taken again from its whole set,
rarest member first as counted among wide documents, where members that no other wide document has use up the prefix.

Equal sets are first joined into one representative.  Lists give star pairs, each member with one leader, in lists of
wide documents the one whose members stand in most documents; pairs are verified on whole sets, and components
follow.  Then the pairs that are still in different components are verified too, if the places of the shared member
leave enough members for the similarity; so no link that matters to a component is lost, while the pairs within a
group are never listed.  Which members
count as frequent changes the work, never the result.

Defined results: null and blank texts have an empty set and are linked with nothing; a text of fewer words than n is
one n-gram, its whole sequence; rows with the same text share their representative; a null doc_id is never linked; an
empty table gives no row; extra columns are ignored.  Members are 64-bit hashes: two different n-grams of
one corpus of m are taken as one with a chance of m^2 / 2^65.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.llm.common import dropped, map_texts, ready, released, runs, saved, table
from graphdelta.llm.components import components

#: A member in more documents than this is frequent.
LONG_LIST = 16
#: Frequent members that fit a broadcast; with more of them the bound on list lengths doubles until they fit.
MOST_FREQUENT = 1 << 20
#: Bits of the filters that keep lone members and documents without candidates out of the shuffles.
FILTER_BITS = 1 << 26
#: Bytes of text that are hashed at once, and characters of a run of texts.
SLICE, RUN_CHARS = 1 << 19, 400_000
_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53, 0x2545F4914F6CDD1D, 0x369DEA0F31A53F85], dtype=np.uint64)
#: One random number for each byte at each of 64 places of a word, A-Z as a-z, and the bytes that part words.
_PLACES = np.random.default_rng(5).integers(0, 1 << 64, size=(64, 256), dtype=np.uint64)
_PLACES[:, 65:91] = _PLACES[:, 97:123]
_GAPS = np.zeros(256, dtype=bool)
_GAPS[[9, 10, 11, 12, 13, 32]] = True


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(32))


def word_hashes(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first byte of every word of a byte string; a word's bytes are summed by table, a slice at a time."""
    inside = ~_GAPS[raw]
    starts = np.flatnonzero(inside & ~np.concatenate([[False], inside[:-1]]))
    out = np.zeros(len(starts), dtype=np.uint64)
    for at in range(0, len(raw), SLICE):
        here = np.flatnonzero(inside[at : at + SLICE]) + at
        if not len(here):
            continue
        word = np.searchsorted(starts, here[0], "right") - 1
        last = np.searchsorted(starts, here[-1], "right") - 1
        first = np.concatenate([[0], np.searchsorted(here, starts[word + 1 : last + 1])])
        place = here - np.repeat(starts[word : last + 1], np.diff(np.append(first, len(here))))
        value = _PLACES[place & 63, raw[here]]
        if place.max() > 63:
            value = value * (2 * (place >> 6) + 1).astype(np.uint64)
        out[word : last + 1] += np.add.reduceat(value, first)
    return mixed(out), starts


def shingle_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hash of every run of ``size`` words."""
    h = np.full(len(words) - size + 1, np.uint64(size))
    for k in range(size):
        h = mixed(h + words[k : k + len(h)] * _ODD[k % len(_ODD)])
    return h.view(np.int64)


def sets_of(texts: list[str], n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of the word n-grams of all texts, one after the other, and the bounds of each text."""
    parts = [t.encode() for t in texts]
    raw = np.frombuffer(b" ".join(parts) + b" ", dtype=np.uint8)
    begins = np.concatenate([[0], np.cumsum([len(p) + 1 for p in parts])]) if parts else np.zeros(1, dtype=np.int64)
    with np.errstate(over="ignore"):
        words, starts = word_hashes(raw)
        cuts = np.searchsorted(starts, begins)
        counts = np.diff(cuts)
        sizes = np.maximum(counts - n + 1, (counts > 0).astype(counts.dtype))
        bounds = np.concatenate([[0], np.cumsum(sizes)])
        out = np.empty(bounds[-1], dtype=np.int64)
        grams = shingle_hashes(words, n) if len(words) >= n else np.empty(0, dtype=np.int64)
        for i in np.flatnonzero(counts).tolist():
            a, b, mine = cuts[i], cuts[i + 1], out[bounds[i] : bounds[i + 1]]
            mine[:] = grams[a : b - n + 1] if b - a >= n else shingle_hashes(words[a:b], b - a)
            mine.sort()
    fresh = np.ones(len(out), dtype=bool)
    fresh[1:] = out[1:] != out[:-1]
    fresh[bounds[:-1][sizes > 0]] = True
    return out[fresh], np.concatenate([[0], np.cumsum(fresh)])[bounds]


def members(text: str | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of a text's word n-grams, as signed numbers."""
    return sets_of([text or ""], n)[0]


def as_lists(values: np.ndarray, bounds: np.ndarray):
    """An Arrow column of number lists."""
    import pyarrow as pa

    return pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(values))


def base_length(size: int, percent: int) -> int:
    """Members outside the least overlap that a partner must have: n - ceil(t n)."""
    return size - -(-percent * size // 100)


def spare_length(size: int, percent: int) -> int:
    """How many more members a document may look at."""
    return base_length(size, percent) // 2 + 2


def digest(h: np.ndarray) -> tuple[int, int]:
    from xxhash import xxh3_128_digest

    return tuple(np.frombuffer(xxh3_128_digest(h.tobytes()), dtype=np.int64).tolist())


def prefixes(docs: DataFrame, n: int, percent: int) -> DataFrame:
    """doc_id, n_shingles, the digest of the set, and the longest prefix any choice can need."""

    def make(texts: list[str]) -> dict:
        values, bounds = sets_of(texts, n)
        sets = [values[a:b] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        keys = [digest(h) for h in sets]
        most = [h[: base_length(len(h), percent) + spare_length(len(h), percent)] for h in sets]
        prefix = as_lists(np.concatenate([values[:0], *most]), np.concatenate([[0], np.cumsum([len(h) for h in most])]))
        return {"n_shingles": np.diff(bounds), "k1": [k[0] for k in keys], "k2": [k[1] for k in keys], "prefix": prefix}

    return map_texts(docs, ("doc_id",), make, "n_shingles long, k1 long, k2 long, prefix array<long>", RUN_CHARS)


def shared_members(reps: DataFrame) -> DataFrame:
    """(m, count) of the members that stand in more than one prefix."""
    return saved(reps.select(F.explode("prefix").alias("m")).groupBy("m").count().filter("count > 1"), "shared")


def frequent_members(counts: DataFrame) -> np.ndarray:
    """Sorted members in more than LONG_LIST prefixes, at most MOST_FREQUENT of them."""
    bound = LONG_LIST
    while counts.filter(F.col("count") > bound).count() > MOST_FREQUENT:
        bound *= 2
    return np.sort(np.array(counts.filter(F.col("count") > bound).select("m").toPandas()["m"], dtype=np.int64))


def choice(prefix: np.ndarray, size: int, percent: int, frequent: np.ndarray) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Rare and frequent members under which a document enters the lists, how much longer its prefix is, and how many
    frequent members that prefix has.  The length that leaves the most members to be shared is taken."""
    base = base_length(size, percent)
    common = np.zeros(len(prefix), dtype=bool)
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, prefix), len(frequent) - 1)
        common = frequent[at] == prefix
    # partners may be smaller by t, and must have looked as far
    farthest = min(spare_length(-(-percent * size // 100), percent), len(prefix) - base)
    before = np.concatenate([[0], np.cumsum(common)])
    k = np.arange(1, farthest + 1)
    surely = k - before[base + k]  # rare members that a partner must share under each choice
    if farthest and surely.max() > 0:
        best = int(k[np.argmax(surely)])
        return prefix[: base + best][~common[: base + best]], prefix[:0], best, int(before[base + best])
    return prefix[~common], prefix[: base + 1][common[: base + 1]], len(prefix) - base, int(before[-1])


class Bitmap:
    """Fixed-size filter over numbers: what it lacks is surely not in the set."""

    def __init__(self, numbers: DataFrame):
        slot = F.col("x").bitwiseXOR(F.shiftrightunsigned("x", 31)).bitwiseAND(FILTER_BITS - 1)
        rows = numbers.select(slot.alias("s")).distinct().groupBy(F.shiftright("s", 15).alias("b")).agg(F.bitmap_construct_agg(F.col("s").bitwiseAND(32767)).alias("bits")).collect()
        self.bits = np.zeros(FILTER_BITS // 8, dtype=np.uint8)
        for r in rows:
            self.bits[r["b"] * 4096 : r["b"] * 4096 + 4096] = np.frombuffer(r["bits"], dtype=np.uint8)

    def has(self, x: np.ndarray) -> np.ndarray:
        slot = (x ^ (x.view(np.uint64) >> np.uint64(31)).view(np.int64)) & (FILTER_BITS - 1)
        return (self.bits[slot >> 3] >> (slot & 7).astype(np.uint8)) & 1 == 1


def listed(reps: DataFrame, percent: int, frequent: np.ndarray, repeated: Bitmap) -> DataFrame:
    """(m, common, rep, k, often) rows of the lists; members that stand in one prefix only are left out early."""
    shared = reps.sparkSession.sparkContext.broadcast((frequent, repeated))

    def run(frames):
        often_known, filter_ = shared.value
        for part in frames:
            m, common, rep, ks, hs = [], [], [], [], []
            for doc, size, prefix in zip(part["rep"], part["n_shingles"], part["prefix"], strict=True):
                rare, often, k, h = choice(np.asarray(prefix, dtype=np.int64), size, percent, often_known)
                rare = rare[filter_.has(rare)]
                m += [rare, often]
                common.append(np.repeat([False, True], [len(rare), len(often)]))
                rep.append(np.full(len(rare) + len(often), doc))
                ks.append(np.full(len(rare) + len(often), k))
                hs.append(np.full(len(rare) + len(often), h))
            if m:
                yield pd.DataFrame({"m": np.concatenate(m), "common": np.concatenate(common), "rep": np.concatenate(rep), "k": np.concatenate(ks), "often": np.concatenate(hs)})

    return reps.select("rep", "n_shingles", "prefix").mapInPandas(run, "m long, common boolean, rep long, k int, often int")


def likely(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """The pairs whose prefixes share enough members for the similarity; never drops a pair that reaches it.

    Up to the lesser end of two prefixes both sets are known: what lies beyond can add at most the shorter rest.
    """
    own = lambda x: reps.select(F.col("rep").alias(x), F.col("n_shingles").alias(f"n{x}"), F.col("prefix").alias(f"p{x}"))
    two = pairs.join(own("b"), "b").join(own("a"), "a")
    end = lambda x: F.when(F.size(f"p{x}") == F.col(f"n{x}"), F.lit((1 << 63) - 1)).otherwise(F.element_at(f"p{x}", -1))
    two = two.withColumn("h", F.least(end("a"), end("b")))
    upto = lambda c: F.size(F.filter(c, lambda m: m <= F.col("h")))
    most = upto(F.array_intersect("pa", "pb")) + F.least(F.col("na") - upto(F.col("pa")), F.col("nb") - upto(F.col("pb")))
    return two.filter((100 + percent) * most >= percent * (F.col("na") + F.col("nb"))).select("a", "b")


def whole_sets(docs: DataFrame, ids: DataFrame, n: int) -> DataFrame:
    """(id, hs), the whole sets of the documents ``ids`` and of few others; only they are hashed and moved."""
    wanted = docs.sparkSession.sparkContext.broadcast(Bitmap(ids.select(F.col("id").alias("x"))))

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            batch = batch.filter(pa.array(wanted.value.has(batch.column("doc_id").to_numpy(zero_copy_only=False))))
            ids, at = batch.column("doc_id"), 0
            for texts in runs(batch.column("text").to_pylist(), RUN_CHARS):
                yield pa.RecordBatch.from_arrays([ids.slice(at, len(texts)), as_lists(*sets_of(texts, n))], names=["id", "hs"])
                at += len(texts)

    return docs.filter(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "id long, hs array<long>")


def ordered(docs: DataFrame, ids: DataFrame, n: int, percent: int) -> DataFrame:
    """(m, rep, size, at, weight) of the prefixes of the documents ``ids``, rarest member first.

    Members are counted among these documents.  Those of one document only come first and are left out of the lists, but
    keep their places ``at``; a document with too many of them can have no link.  ``weight`` is the mean count of a
    document's members: the centre of a group of near copies has the greatest.
    """
    own = whole_sets(docs, ids, n).join(ids, "id", "left_semi").dropDuplicates(["id"])
    each = saved(own.select(F.col("id").alias("rep"), F.size("hs").alias("size"), F.explode("hs").alias("m")), "wide")
    known = each.join(each.groupBy("m").agg(F.count(F.lit(1)).alias("c")), "m")
    sets = known.groupBy("rep", "size").agg(F.sort_array(F.collect_list(F.struct("c", "m"))).alias("x"), F.avg("c").alias("weight"))
    least = F.expr(f"({percent} * size + 99) div 100")  # members to be shared with any partner, and the least partner's size
    lone = F.size(F.filter("x", lambda q: q["c"] == 1))
    able = sets.filter((100 + percent) * (F.col("size") - lone) >= percent * (F.col("size") + least))
    placed = able.select("rep", "size", "weight", F.posexplode(F.slice("x", F.lit(1), (F.col("size") - least + 1).cast("int"))).alias("at", "q"))
    lists = saved(placed.filter("q.c > 1").select("q.m", "rep", "size", "at", "weight"), "ordered")
    dropped(each)
    return lists


def verified(docs: DataFrame, pairs: DataFrame, n: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose whole sets reach the similarity."""
    ids = pairs.select(F.col("a").alias("id")).unionByName(pairs.select(F.col("b").alias("id"))).distinct()
    sets = saved(whole_sets(docs, ids, n), "sets")
    two = pairs.join(sets.select(F.col("id").alias("b"), F.col("hs").alias("hb")), "b")
    two = two.join(sets.select(F.col("id").alias("a"), F.col("hs").alias("ha")), "a")
    shared = F.size(F.array_intersect("ha", "hb"))
    links = saved(two.filter(100 * shared >= percent * (F.size("ha") + F.size("hb") - shared)).select("a", "b").distinct(), "links")
    dropped(sets)
    return links


def join(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id of every row: the least doc_id reachable by links, itself included."""
    spark = docs.sparkSession
    ready(spark)
    full = saved(prefixes(docs, n, percent), "prefixes")
    reps = saved(full.filter((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull()).groupBy("k1", "k2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.any_value("prefix").alias("prefix")), "reps")
    counts = shared_members(reps)
    frequent, repeated = frequent_members(counts), Bitmap(counts.select(F.col("m").alias("x")))
    lists = saved(listed(reps, percent, frequent, repeated), "lists")
    dropped(counts)
    released(spark)
    # lists of rare members are short: LONG_LIST, unless too many members were frequent
    groups = saved(lists.filter("not common").groupBy("m").agg(F.sort_array(F.collect_list(F.struct("rep", "k", "often"))).alias("reps")).filter(F.size("reps") > 1).groupBy("reps").agg(F.count(F.lit(1)).alias("w")), "groups")
    often = ordered(docs, lists.filter("common").select(F.col("rep").alias("id")).distinct(), n, percent)
    dropped(lists)

    def placed(df: DataFrame, comp: DataFrame | None) -> DataFrame:
        if comp is None:
            return df.withColumn("component", F.col("rep"))
        return df.join(comp.select(F.col("id").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))

    links, tried, comp = None, None, None
    for leader in (F.min, F.max, None):
        spread = placed(groups.select(F.xxhash64("reps").alias("g"), "w", F.explode("reps").alias("r")).select("g", "w", "r.*"), comp)
        mixed_groups = spread.groupBy("g").agg(F.sort_array(F.collect_list(F.struct("rep", "component", "k", "often"))).alias("x"), F.max("w").alias("w"), F.min("component").alias("c"), F.max("component").alias("d")).filter("c < d")
        wide = placed(often, comp)
        split = wide.groupBy("m").agg(F.min("component").alias("c"), F.max("component").alias("d")).filter("c < d").select("m")
        left = wide.join(split, "m", "left_semi")
        if leader is not None:
            # a star: each member with one leader of one of its lists
            end = F.element_at("x", 1 if leader is F.min else -1)
            star = mixed_groups.select(end.alias("l"), F.explode("x").alias("p")).select("l.rep", "l.component", F.col("p.rep").alias("b"), F.col("p.component").alias("cb"))
            rank = F.struct("weight", "size", "rep", "component") if leader is F.min else F.struct("size", "weight", "rep", "component")
            ends = left.groupBy("m").agg(F.max(rank).alias("l"))
            far = left.select("m", F.col("rep").alias("b"), F.col("component").alias("cb")).join(ends, "m").filter("l.rep != b and l.component != cb")
            pairs = star.filter("rep != b and component != cb").groupBy("b").agg(leader("rep").alias("rep"))
            pairs = pairs.unionByName(far.groupBy("b").agg(F.max("l").alias("l")).select("b", "l.rep")).select(F.least("rep", "b").alias("a"), F.greatest("rep", "b").alias("b"))
        else:
            # pairs with the number of rare members they share; the prefixes tell how many it must be
            both = mixed_groups.select("x", "w", F.posexplode("x").alias("i", "p")).select(
                "w", "p", F.explode(F.filter(F.slice("x", F.col("i") + 2, F.lit(1 << 30)), lambda q: q["component"] != F.col("p.component"))).alias("q")
            )
            must = F.least("p.k", "q.k") - F.least("p.often", "q.often")
            cross = both.groupBy(F.col("p.rep").alias("a"), F.col("q.rep").alias("b"), must.alias("must")).agg(F.sum("w").alias("w")).filter(F.col("w") >= F.greatest("must", F.lit(1)))
            # at the first shared member of a pair no more than the rest of either set can be shared
            side = lambda x: left.select("m", F.col("rep").alias(x), F.col("component").alias(f"c{x}"), F.col("size").alias(f"n{x}"), (F.col("size") - F.col("at")).alias(f"r{x}"))
            over = side("a").join(side("b"), "m").filter(f"a < b and ca != cb and {100 + percent} * least(ra, rb) >= {percent} * (na + nb)")
            pairs = cross.select("a", "b").unionByName(over.select("a", "b"))
        pairs = pairs.distinct()
        pairs = saved(pairs if tried is None else pairs.join(tried, ["a", "b"], "left_anti"), "pairs")
        tried = pairs if tried is None else tried.unionByName(pairs)
        close = saved(likely(pairs, reps, percent), "close")
        if not close.limit(1).count():
            continue
        new = verified(docs, close, n, percent)
        released(spark)
        links = new if links is None else links.unionByName(new)
        comp = saved(components(links), "components")
    rows = full.select("doc_id", "n_shingles", "k1", "k2")
    keys = reps.select("k1", "k2", "n_shingles", "rep")
    of_set = placed(keys, comp).select("k1", "k2", "n_shingles", F.col("component").alias("component_id"))
    alone = F.when((F.col("n_shingles") == 0) | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return rows.join(of_set, ["k1", "k2", "n_shingles"], "left").select("doc_id", "n_shingles", alone.alias("component_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(table(spark, sf_dir, "documents"), 3, 90)
