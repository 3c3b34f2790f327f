"""Token counts by prefix dynamic programming.

For every word the table holds, at each of its prefixes, the last token of that prefix's encoding and the number of
tokens so far.  The last token is the one token that ends there, is its own encoding, and stays apart from the last
token before it; so each prefix takes one step from a shorter one and no prefix is encoded again.  Sums of these
counts over the words of a text answer how long a text is, how long any prefix of it is, and how much of it fits a
budget.

The vocabulary is a ``.json`` file whose words end in a marked symbol: text is normalised (NFC, lower case), split
into words, and the last letter of each word carries the mark.  A prefix that ends inside a word counts as the text
cut there would.  Special strings inside a text are one token each.

Defined results: null and empty texts have 0 tokens and 0 bytes; white space has none; texts are taken whole.
"""

from __future__ import annotations

import json
import unicodedata

import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession

from graphdelta.llm.bpe import byte_letters, vocabulary
from graphdelta.llm.common import map_texts, table

#: The word pattern of the file, and the mark of a word's last letter.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"""
END = "</w>"
LIMIT = 2048
#: Words and token pairs that a worker remembers; past it the memory is emptied.
REMEMBERED = 600_000
#: Rank of a merge that never comes.
NEVER = 1 << 40


#: Lower case as the library has it where ``str.lower`` differs: sigma letter by letter, and two letters newer than Python's tables.
NEWER = (("\u03a3", "\u03c3"), ("\ua7cb", "\u0264"), ("\ua7dc", "\u019b"))


class PrefixCounter:
    """Prefix tables of one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.vocab: dict[str, int] = spec["model"]["vocab"]
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
        self.rank = {p: i for i, p in reversed(list(enumerate(pairs)))}
        self.letters = byte_letters()
        self.table = str.maketrans({b: c for b, c in enumerate(self.letters)})
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.words = regex.compile(SPLIT)
        self.marks = regex.compile("|".join(regex.escape(x) for x in sorted(self.special, key=len, reverse=True)))
        self.longest = max(len(t.removesuffix(END)) for t in self.vocab)
        self.spines: dict[str, tuple | None] = {}
        self.apart: dict[str, dict[str, bool]] = {}
        self.pairs = 0
        self.known: dict[str, int] = {}
        #: True for tokens that are their own encoding, False for what only begins one.
        self.starts: dict[str, bool] = {}
        for token in self.vocab:
            if not token.endswith(END) and self.spine(token):
                for n in range(1, len(token)):
                    self.starts.setdefault(token[:n], False)
                self.starts[token] = True

    def symbols(self, token: str) -> list[str]:
        return [*token[: -len(END) - 1], token[-len(END) - 1 :]] if token.endswith(END) else [*token]

    def merged(self, symbols: list[str]) -> list[str]:
        """Plain merging of a short sequence: what the stability tests are decided by."""
        while len(symbols) > 1:
            ranks = [self.rank.get(p, len(self.rank)) for p in zip(symbols, symbols[1:])]
            low = min(ranks)
            if low == len(self.rank):
                break
            i = ranks.index(low)
            symbols[i : i + 2] = [symbols[i] + symbols[i + 1]]
        return symbols

    def spine(self, token: str) -> tuple | None:
        """The token's outer pieces while it is merged, or None if it is not its own encoding.

        Two lists, along its right and its left edge: (piece, rank of the merge that ends it), shortest piece first.
        The third item tells whether ranks only rise along both, as they do in trained vocabularies.
        """
        if token in self.spines:
            return self.spines[token]
        found = None
        if token in self.vocab:
            nodes: list[tuple] = [(s, -1, None, None) for s in self.symbols(token)]
            while len(nodes) > 1:
                ranks = [self.rank.get((x[0], y[0]), NEVER) for x, y in zip(nodes, nodes[1:])]
                low = min(ranks)
                if low == NEVER:
                    break
                i = ranks.index(low)
                nodes[i : i + 2] = [(nodes[i][0] + nodes[i + 1][0], low, nodes[i], nodes[i + 1])]
            if len(nodes) == 1:
                edges = []
                for side in (3, 2):
                    node, edge, ends = nodes[0], [], NEVER
                    while node:
                        edge.append((node[0], ends))
                        ends, node = node[1], node[side]
                    edges.append(edge[::-1])
                rising = all(x[1] < y[1] for e in edges for x, y in zip(e, e[1:]))
                found = (*edges, rising)
        self.spines[token] = found
        return found

    def stays(self, left: str, right: str) -> bool:
        """Whether two tokens side by side stay as they are.

        They do unless, while both are being merged, a piece at the end of the left one and a piece at the start of the
        right one stand together and their own merge ranks before the merges that end those pieces.
        """
        after = self.apart.get(left)
        if after is None:
            after = self.apart[left] = {}
        if (known := after.get(right)) is None:
            self.pairs += 1
            if self.pairs > REMEMBERED:
                self.apart, self.pairs = {left: after}, 0
                after.clear()
            ends, starts = self.spine(left), self.spine(right)
            if ends[2] and starts[2]:
                known = self.meet(ends[0], starts[1])
            else:
                known = self.merged(self.symbols(left) + self.symbols(right)) == [left, right]
            after[right] = known
        return known

    def meet(self, ends: list, starts: list) -> bool:
        i = j = 0
        while True:
            (x, x_ends), (y, y_ends) = ends[i], starts[j]
            rank = self.rank.get((x, y), NEVER)
            if rank < x_ends and rank <= y_ends and rank < NEVER:
                return False
            if x_ends == y_ends == NEVER:
                return True
            if x_ends <= y_ends:
                i += 1
            else:
                j += 1

    def prefix_table(self, word: str) -> tuple[list[str], list[int]]:
        """Last token and token count at every prefix of a word without its end mark."""
        n = len(word)
        last, count = [""] * (n + 1), [0] * (n + 1)
        begins, stays, longest = self.starts.get, self.stays, self.longest
        for start in range(n):
            before, so_far = last[start], count[start] + 1
            if start and not before:
                raise ValueError(f"the vocabulary lacks a letter of {word[:start]!r}")
            for end in range(start + 1, min(n, start + longest) + 1):
                token = word[start:end]
                whole = begins(token)
                if whole is None:
                    break
                if whole and not last[end] and (not start or stays(before, token)):
                    last[end], count[end] = token, so_far
        return last, count

    def marked(self, word: str, last: list[str], count: list[int], end: int) -> int:
        """Tokens of the word cut after ``end`` letters, its last letter marked: one step from the table."""
        for start in range(max(0, end - self.longest), end):
            token = word[start:end] + END
            if token in self.vocab and self.spine(token) and (not start or self.stays(last[start], token)):
                return count[start] + 1
        raise ValueError(f"the vocabulary lacks the end of {word[:end]!r}")

    def spelled(self, word: str) -> str:
        return word if word.isascii() and word.isprintable() else word.encode("utf-8").decode("latin-1").translate(self.table)

    def of_word(self, word: str) -> int:
        """Tokens of one word."""
        spelled = self.spelled(word)
        return self.marked(spelled, *self.prefix_table(spelled), len(spelled))

    def normal(self, text: str) -> str:
        if text.isascii():
            return text.lower()
        text = unicodedata.normalize("NFC", text)
        for capital, small in NEWER:
            text = text.replace(capital, small)
        return text.lower()

    def parts(self, text: str) -> list[str | None]:
        """Stretches of ordinary text, with None for each special string."""
        if not any(x in text for x in self.special):
            return [text]
        out: list[str | None] = []
        at = 0
        for m in self.marks.finditer(text):
            out += [text[at : m.start()], None]
            at = m.end()
        return [*out, text[at:]]

    def count(self, text: str) -> int:
        """Tokens of a whole text."""
        total, known = 0, self.known
        for part in self.parts(text):
            if part is None:
                total += 1
            else:
                words = self.words.findall(self.normal(part))
                try:
                    total += sum(map(known.__getitem__, words))
                except KeyError:
                    distinct = set(words)
                    if len(known) + len(distinct) > REMEMBERED:
                        known.clear()
                    for word in [w for w in distinct if w not in known]:
                        known[word] = self.of_word(word)
                    total += sum(map(known.__getitem__, words))
        return total

    def prefix_counts(self, text: str) -> np.ndarray:
        """Token count of every prefix of a normalised text without special strings, by number of characters."""
        if self.normal(text) != text or len(self.parts(text)) > 1:
            raise ValueError("prefix counts need normalised text without special strings")
        out, before = np.zeros(len(text) + 1, dtype=np.int64), 0
        filled = 0
        for m in self.words.finditer(text):
            word = m.group()
            if word[0] == "'" and len(word) > 1 or not word[0].isalnum():
                # a cut inside these can change where words split
                sizes = [sum(map(self.of_word, self.words.findall(word[:n]))) for n in range(1, len(word) + 1)]
            else:
                spelled = self.spelled(word)
                last, count = self.prefix_table(spelled)
                ends = np.cumsum([len(c.encode("utf-8")) for c in word])
                sizes = [self.marked(spelled, last, count, int(e)) for e in ends]
            out[filled : m.start() + 1] = before
            out[m.start() + 1 : m.end() + 1] = before + np.array(sizes)
            before, filled = before + sizes[-1], m.end() + 1
        out[filled:] = before
        return out

    def fitting(self, text: str, budget: int) -> int:
        """Characters of the longest prefix within a token budget."""
        return int(np.flatnonzero(self.prefix_counts(text) <= budget)[-1])


_LOADED: dict[str, PrefixCounter] = {}


def loaded(path: str) -> PrefixCounter:
    if path not in _LOADED:
        _LOADED[path] = PrefixCounter(path)
    return _LOADED[path]


def count_table(docs: DataFrame, path: str, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every row."""

    def make(texts: list[str]) -> dict:
        tool = loaded(path)
        tokens = np.array([tool.count(t) for t in texts], dtype=np.int64)
        return {"n_bytes": [len(t.encode()) for t in texts], "n_tokens": tokens, "over_limit": tokens > limit}

    return map_texts(docs, ("doc_id",), make, "n_bytes long, n_tokens long, over_limit boolean")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_table(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"))
