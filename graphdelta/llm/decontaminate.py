"""Benchmark decontamination by SimHash of item-sized windows and a multi-index of the items' fingerprints.

Windows as long as an item slide over every text.  A window and an item have 128-bit SimHashes of their words; a
multi-index of eight blocks of 16 bits names every item whose fingerprint lies within ``RADIUS`` bits of the
window's: of so many differing bits some block holds an eighth at most, and each block lists the items under all values
that near.  A named pair is verified exactly: items and windows are weighted sets of five-word shingles (a
shingle weighs the letters of its words), and the weight they share must be at least ``SIMILARITY`` of the item's and of
the window's.

A window that shares no shingle with any item of its length has similarity zero, so every window that holds such a
shingle, wherever in it, is fingerprinted and no other is; this leaves out no similar window.  What the radius may lose is
measured by a test against all windows.  The benchmark is the small side: its index is broadcast in parts of
``MOST_ITEMS`` items, and its size is checked against ``MOST_BYTES``; the documents never move.

Defined results: null and blank texts and items match nothing; an item of fewer than five words is one shingle, its
whole sequence; a text shorter than an item is one window; equal items are each reported; repeated documents are each
reported, with a null doc_id too; an empty benchmark or table gives no row; extra columns are ignored; a text is searched
whole, whatever its length.
"""

from __future__ import annotations

from collections import defaultdict
from functools import cached_property
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.llm.common import filter_texts, map_texts, table

SHINGLE, SIMILARITY = 5, 0.8
#: Bits of a fingerprint, of a block of it, and by how many bits a window may differ from an item it is verified with.
BITS, BLOCK_BITS, RADIUS = 128, 16, 31
#: Windows that are fingerprinted at once.
STEP = 2048
#: Most text the benchmark may have, and the items of one index, which every worker holds (22 kB an item).
MOST_BYTES, MOST_ITEMS = 256 << 20, 4000


def words_of(text: str | None) -> list[bytes]:
    """Words between ASCII white space, A-Z lower-cased: what bytes offer without touching other letters."""
    return (text or "").encode().lower().split()


def shingles(words: list[bytes]) -> list[tuple[bytes, ...]]:
    if not words:
        return []
    return [tuple(words[i : i + SHINGLE]) for i in range(max(1, len(words) - SHINGLE + 1))]


def weight(shingle: tuple[bytes, ...]) -> int:
    return sum(map(len, shingle))


def word_signs(words: list[bytes]) -> np.ndarray:
    """One row of ``BITS`` signs a word."""
    from xxhash import xxh3_128_digest

    raw = np.frombuffer(b"".join(map(xxh3_128_digest, words)), dtype=np.uint8).reshape(len(words), BITS // 8)
    return np.unpackbits(raw, axis=1).astype(np.int32) * 2 - 1


def fingerprints(words: list[bytes], starts: np.ndarray, n: int) -> np.ndarray:
    """SimHash blocks of the windows of n words at ``starts``, ascending."""
    low = int(starts[0])
    sums = np.zeros((int(starts[-1]) + n - low + 1, BITS), dtype=np.int32)
    np.cumsum(word_signs(words[low : int(starts[-1]) + n]), axis=0, out=sums[1:])
    at = starts - low
    return np.packbits(sums[at + n] > sums[at], axis=1).view(np.uint16)


class MultiIndex:
    """Which fingerprints lie within ``radius`` bits of another one; only the fingerprints travel, the tables are made again."""

    def __init__(self, prints: np.ndarray, radius: int = RADIUS):
        self.prints, self.radius = prints, radius

    def __getstate__(self):
        return {"prints": self.prints, "radius": self.radius}

    @cached_property
    def tables(self) -> list[tuple[np.ndarray, np.ndarray]]:
        """Of each block: the fingerprints that have a value near each value, in the order of the values, and their bounds."""
        blocks = self.prints.shape[1]
        near = [sum(1 << b for b in bits) for k in range(self.radius // blocks + 1) for bits in combinations(range(BLOCK_BITS), k)]
        out = []
        for b in range(blocks):
            keys = (self.prints[:, b, None] ^ np.array(near, dtype=np.uint16)).ravel()
            order = np.argsort(keys, kind="stable")
            out.append(((order // len(near)).astype(np.int32), np.searchsorted(keys[order], np.arange((1 << BLOCK_BITS) + 1)).astype(np.int32)))
        return out

    def within(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row of ``prints``, place of an indexed one) of every pair within the radius."""
        rows, places = [], []
        for b, (holders, bounds) in enumerate(self.tables):
            low = bounds[prints[:, b]].astype(np.int64)
            count = bounds[prints[:, b].astype(np.int64) + 1] - low
            row = np.repeat(np.arange(len(prints)), count)
            inside = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
            rows.append(row)
            places.append(holders[np.repeat(low, count) + inside])
        pairs = np.unique(np.concatenate(rows) * np.int64(len(self.prints)) + np.concatenate(places))
        row, place = pairs // len(self.prints), pairs % len(self.prints)
        near = np.bitwise_count(prints[row] ^ self.prints[place]).sum(axis=1) <= self.radius
        return row[near], place[near]


class ItemIndex:
    """The items, the lengths at which a shingle stands in one, and a multi-index of the items."""

    def __init__(self, items: list[tuple[int, str]], similarity: float = SIMILARITY, radius: int = RADIUS):
        self.similarity = similarity
        self.items: list[tuple[int, dict[tuple[bytes, ...], int], int]] = []
        lengths: dict[tuple[bytes, ...], set[int]] = defaultdict(set)
        sizes, prints = [], []
        for item_id, text in items:
            words = words_of(text)
            own = {s: weight(s) for s in shingles(words)}
            if own:
                for s in own:
                    lengths[s].add(len(words))
                sizes.append(len(words))
                self.items.append((item_id, own, sum(own.values())))
                prints.append(fingerprints(words, np.zeros(1, dtype=np.int64), len(words))[0])
        self.lengths = {s: tuple(sorted(n)) for s, n in lengths.items()}
        self.vocabulary = {w for s in self.lengths for w in s}
        self.sizes = np.array(sizes, dtype=np.int64)
        self.short = sorted({n for n in sizes if n < SHINGLE})
        self.index = MultiIndex(np.array(prints, dtype=np.uint16).reshape(len(prints), BITS // BLOCK_BITS), radius)

    def places(self, words: list[bytes]) -> dict[int, list[int]]:
        """Where a text holds shingles of items, by the items' length."""
        hits: dict[int, list[int]] = defaultdict(list)
        get = self.lengths.get
        if len(words) >= SHINGLE:
            known = np.fromiter(map(self.vocabulary.__contains__, words), dtype=bool, count=len(words))
            runs = np.convolve(known, np.ones(SHINGLE, dtype=np.int64), "valid") == SHINGLE
            for at in np.flatnonzero(runs).tolist():  # only five benchmark words in a row can be a shingle
                for n in get(tuple(words[at : at + SHINGLE]), ()):
                    hits[n].append(at)
        for n in self.short:
            for at in range(len(words) - n + 1):
                if n in get(tuple(words[at : at + n]), ()):
                    hits[n].append(at)
        return hits

    def search(self, text: str | None) -> list[tuple[int, int, int, float]]:
        """(item, first word, number of words, similarity): each item's best window in a text, the first of equals."""
        words = words_of(text)
        best: dict[int, tuple[float, int, int]] = {}
        for n, places in (self.places(words) if words and self.items else {}).items():
            size, last = min(n, len(words)), max(0, len(words) - n)
            held = np.zeros(last + 2, dtype=np.int64)  # starts of the windows that hold a place, as steps up and down
            at = np.array(places)
            np.add.at(held, np.minimum(np.maximum(0, at - size + min(n, SHINGLE)), last), 1)
            np.add.at(held, np.minimum(at, last) + 1, -1)
            starts = np.flatnonzero(np.cumsum(held)[:-1] > 0)
            for k in range(0, len(starts), STEP):
                some = starts[k : k + STEP]
                gaps = np.flatnonzero(np.diff(some) > 4 * n) + 1
                for part in np.split(some, gaps):
                    rows, found = self.index.within(fingerprints(words, part, size))
                    fits = self.sizes[found] == n
                    for first, i in zip(part[rows[fits]].tolist(), found[fits].tolist(), strict=True):
                        similar = self.similar(words[first : first + size], i)
                        if similar >= self.similarity and (similar, -first) > best.get(i, (0.0, 0, 0))[:2]:
                            best[i] = (similar, -first, size)
        return [(self.items[i][0], -first, size, similar) for i, (similar, first, size) in sorted(best.items())]

    def similar(self, window: list[bytes], i: int) -> float:
        """Shared shingle weight over the heavier of window and item."""
        _, own, total = self.items[i]
        mine = set(shingles(window))
        shared = sum(own[s] for s in mine & own.keys())
        return shared / max(total, sum(map(weight, mine)))


def build(items: DataFrame, similarity: float = SIMILARITY) -> list[ItemIndex]:
    """Indexes over the parts of a benchmark table (item_id, text) whose size is checked first."""
    size = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if size > MOST_BYTES:
        raise ValueError(f"the benchmark has {size} bytes of text; split it into parts of at most {MOST_BYTES}")
    rows = [(r["item_id"], r["text"] or "") for r in items.select("item_id", "text").orderBy("item_id").collect()]
    return [ItemIndex(rows[at : at + MOST_ITEMS], similarity) for at in range(0, len(rows), MOST_ITEMS)]


def find(docs: DataFrame, indexes: list[ItemIndex]) -> DataFrame:
    """doc_id, item_id, first_word, n_words, similarity: one row per document and benchmark item found in it."""
    shared = docs.sparkSession.sparkContext.broadcast(indexes)
    hit = "array<struct<item_id:long,first_word:long,n_words:long,similarity:double>>"

    def make(texts: list[str]) -> dict:
        names = ("item_id", "first_word", "n_words", "similarity")
        return {"hits": [[dict(zip(names, h, strict=True)) for index in shared.value for h in index.search(t)] for t in texts]}

    found = map_texts(docs, ("doc_id",), make, f"hits {hit}")
    return found.select("doc_id", F.explode("hits").alias("h")).select("doc_id", "h.*")


def clean(docs: DataFrame, indexes: list[ItemIndex]) -> DataFrame:
    """The rows of ``docs``, all columns, in whose text no item is found."""
    shared = docs.sparkSession.sparkContext.broadcast(indexes)
    return filter_texts(docs, lambda texts: [not any(index.search(t) for index in shared.value) for t in texts])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(table(spark, sf_dir, "documents"), build(table(spark, sf_dir, "benchmark")))
