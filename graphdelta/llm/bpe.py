"""Byte-level BPE encoding and decoding in batched numpy merge rounds.

The words of a batch of texts are encoded together: their bytes lie in one flat symbol array, every round looks up
all neighbouring pairs by binary search over the sorted pair keys, keeps for each word its lowest rank, and merges
that pair wherever it stands in the word, leftmost first.  A word leaves the array once no pair of it can merge.

Results equal those of the public tokenizers library for a byte-level ``.json`` file: special strings inside a text
become their own id, no other ids are added, and decoding keeps special ids.  Null and empty texts give no ids, and
the empty string back.  Texts of any length are taken whole: memory is bounded by the largest text in a batch.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterable

import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession

from graphdelta.llm.common import map_texts, table

#: Fixed value: the pattern that splits text before the merges of a byte-level file.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Words whose ids a worker remembers; past it the memory is emptied.
REMEMBERED = 400_000


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in a byte-level vocabulary."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class ByteBpe:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        letters = byte_letters()
        to_byte = {c: b for b, c in enumerate(letters)}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.first = np.array([vocab[c] for c in letters], dtype=np.int64)
        self.base = 1 + max([*vocab.values(), *self.special.values()])
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in merges]
        keys = np.array([vocab[a] * self.base + vocab[b] for a, b in pairs], dtype=np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], dtype=np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank, self.by_rank = keys[order], order.astype(np.int64), made
        pieces = [b""] * self.base
        for token, i in vocab.items():
            pieces[i] = bytes(to_byte[c] for c in token)
        for token, i in self.special.items():
            pieces[i] = token.encode()
        self.pieces = pieces
        self.words = regex.compile(SPLIT)
        self.marks = regex.compile("(" + "|".join(regex.escape(x) for x in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        self.known: dict[str, bytes] = {}

    def merge(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of every word; all words of the list move through the rounds together."""
        none = len(self.keys)
        sizes = np.array([len(w) for w in words], dtype=np.int64)
        symbols = self.first[np.frombuffer(b"".join(words), dtype=np.uint8)]
        owner = np.repeat(np.arange(len(words)), sizes)
        rank = np.full(len(symbols), none, dtype=np.int64)  # of each symbol with the next one of its word
        again = np.flatnonzero(owner[1:] == owner[:-1])  # pairs to look up
        done_symbols, done_owner = [], []
        while len(symbols):
            key = symbols[again] * self.base + symbols[again + 1]
            at = np.minimum(np.searchsorted(self.keys, key), none - 1)
            rank[again] = np.where(self.keys[at] == key, self.rank[at], none)
            starts = np.flatnonzero(np.diff(owner, prepend=-1))
            best = np.minimum.reduceat(rank, starts)
            size = np.diff(starts, append=len(owner))
            each = np.repeat(best, size)
            live = each < none
            if not live.all():
                done_symbols.append(symbols[~live])
                done_owner.append(owner[~live])
            left = np.flatnonzero(live & (rank == each))
            if len(left) > 1:  # in a run such as a a a only every other pair merges, from the left
                first = np.flatnonzero(np.diff(left, prepend=left[0] - 2) != 1)
                place = np.arange(len(left)) - np.repeat(first, np.diff(first, append=len(left)))
                left = left[place % 2 == 0]
            symbols[left] = self.by_rank[rank[left]]
            changed = np.zeros(len(symbols), dtype=bool)
            changed[left] = True
            live[left + 1] = False
            rank[left] = none
            symbols, owner, rank, changed = symbols[live], owner[live], rank[live], changed[live]
            changed[:-1] |= changed[1:]
            again = np.flatnonzero(changed[:-1] & (owner[1:] == owner[:-1]))
            rank[:-1][changed[:-1]] = none
            rank[-1:] = none
        if not done_symbols:
            return [np.empty(0, dtype=np.int64) for _ in words]
        flat, own = np.concatenate(done_symbols), np.concatenate(done_owner)
        order = np.argsort(own, kind="stable")
        return np.split(flat[order], np.cumsum(np.bincount(own, minlength=len(words)))[:-1])

    def learn(self, words: Iterable[str]) -> None:
        """Make the little-endian ids of all these words known."""
        new = [w for w in words if w not in self.known]
        if len(self.known) + len(new) > REMEMBERED:
            self.known.clear()
            new = list(words)
        if new:
            raw = [w.encode("utf-8", "surrogatepass") for w in new]
            for word, ids in zip(new, self.merge(raw), strict=True):
                self.known[word] = ids.astype("<u4").tobytes()

    def cut(self, text: str) -> list[str]:
        """Words of a text in order; special strings stand as items of their own."""
        if self.marks is None or not any(x in text for x in self.special):
            return self.words.findall(text)
        out: list[str] = []
        for part in self.marks.split(text):
            out += [part] if part in self.special else self.words.findall(part)
        return out

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Ids of every text as little-endian unsigned 32-bit numbers."""
        cut = [self.cut(t) for t in texts]
        distinct = set().union(*cut)
        marks = {x: np.array([i], dtype="<u4").tobytes() for x, i in self.special.items()}
        self.learn(distinct - marks.keys())
        if marks.keys() & distinct:
            known = {w: self.known[w] for w in distinct - marks.keys()} | marks
            return [b"".join([known[w] for w in ws]) for ws in cut]
        return [b"".join(map(self.known.__getitem__, ws)) for ws in cut]

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_batch([text])[0], dtype="<u4").tolist()

    def decode(self, ids: Iterable[int]) -> str:
        return b"".join([self.pieces[i] for i in ids]).decode("utf-8", "replace")


_LOADED: dict[str, ByteBpe] = {}


def loaded(path: str) -> ByteBpe:
    """The vocabulary of a worker process, read once."""
    if path not in _LOADED:
        _LOADED[path] = ByteBpe(path)
    return _LOADED[path]


def encode_table(docs: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns plus n_tokens, ids (binary, little-endian uint32) of every row's text."""

    def make(texts: list[str]) -> dict:
        ids = loaded(path).encode_batch(texts)
        return {"n_tokens": [len(x) // 4 for x in ids], "ids": ids}

    return map_texts(docs, keep, make, "n_tokens long, ids binary")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every text."""

    def make(texts: list[str]) -> dict:
        tool = loaded(path)
        ids = tool.encode_batch(texts)
        back = [tool.decode(np.frombuffer(x, dtype="<u4").tolist()) for x in ids]
        return {"n_tokens": [len(x) // 4 for x in ids], "ids_sha256": [hashlib.sha256(x).hexdigest() for x in ids], "decoded_sha256": [hashlib.sha256(x.encode()).hexdigest() for x in back]}

    return map_texts(docs, ("doc_id",), make, "n_tokens long, ids_sha256 string, decoded_sha256 string")


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))
