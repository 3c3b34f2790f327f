"""Toxicity by compression distance: two zstandard dictionaries, one of toxic and one of ordinary text.

Every text is cut into overlapping windows of bytes.  A window is compressed with either dictionary; by how many
bytes the toxic one is shorter is the window's distance.  Thresholds on that distance are calibrated by how often
windows of ordinary training text pass them, and a small logistic regression over a text's counts above its expected
counts gives the score.

Both dictionaries are trained by zstandard, one on windows of ordinary texts, one on the passages of toxic texts
whose byte n-grams stand in significantly more toxic texts than ordinary ones.  The toxic side is compressed with the
ordinary dictionary's bytes followed by its own, so ordinary words cost the same under both.  Training texts are a bounded
sample of labelled rows (``MOST_TEXTS`` of each class, by a hash of the id, outside the held-out fold); the model has a
fixed size.  Stride, significance, piece and dictionary sizes were chosen by halves of the training side of one table; level,
window, thresholds and gram size come from an earlier choice that also looked at held-out rows of that table, and the
halves confirmed level and window.

Defined results: null and empty texts have no window and get the score of a text without toxic windows; equal texts
get equal scores; with no toxic or no ordinary training text every score is 0 or 1 after the class there is, and 0
with none; texts are scored whole, whatever their length; rows with a null doc_id are scored, count as held out and teach
nothing; repeated rows get equal scores; an empty table gives no row; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.llm.common import filter_texts, fold, map_texts, table
from graphdelta.llm.learning import Logistic, labelled_ids, texts_of

MOST_TEXTS = 2500
WINDOW, STRIDE, LEVEL = 32, 8, 7
#: Bytes of a byte n-gram and bits of its hash.  Significance is asked for as a share of the greatest there is, so that it does not depend on the number of texts.
GRAM, BITS, SIGNIFICANT = 6, 20, 0.07
TOXIC_BYTES, ORDINARY_BYTES = 4000, 2000
#: Bytes of the pieces that zstandard's trainer picks.
SEGMENT = 24
THRESHOLDS = (2, 3, 4, 5, 6, 8)
DECIDE_AT = 0.5


def plain(text: str) -> bytes:
    """The text as it is compressed: A-Z lower-cased, white space as single spaces, one space around it."""
    return b" " + b" ".join(text.encode().lower().split()) + b" "


def windows(raw: bytes) -> list[bytes]:
    return [raw[i : i + WINDOW] for i in range(0, max(1, len(raw) - WINDOW + STRIDE), STRIDE)] if len(raw) > 2 else []


def gram_ids(raw: bytes) -> np.ndarray:
    b = np.frombuffer(raw, dtype=np.uint8).astype(np.uint64)
    n = len(b) - GRAM + 1
    if n <= 0:
        return np.empty(0, dtype=np.int64)
    h = np.zeros(n, dtype=np.uint64)
    for k in range(GRAM):
        h = h * np.uint64(1099511628211) + b[k : k + n]
    return ((h ^ (h >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BITS)).astype(np.int64)


def significance(toxic: list[bytes], ordinary: list[bytes]) -> np.ndarray:
    """How far each hashed n-gram's number of toxic texts lies over what ordinary texts lead to expect."""
    seen = [np.zeros(1 << BITS), np.zeros(1 << BITS)]
    for counts, texts in zip(seen, (toxic, ordinary), strict=True):
        for t in texts:
            counts[np.unique(gram_ids(t))] += 1
    p = (seen[1] + 1) / (len(ordinary) + 2)
    return (seen[0] - len(toxic) * p) / np.sqrt(len(toxic) * p * (1 - p) + 1)


def passages(toxic: list[bytes], excess: np.ndarray, least: float) -> list[bytes]:
    """What of the toxic texts is not ordinary: their significant stretches, one for each place where one stands.

    A stretch ends where significance falls to half its peak.
    """
    found = []
    for raw in toxic:
        ids = gram_ids(raw)
        hot = np.flatnonzero(excess[ids] >= least)
        if len(hot):
            runs = np.split(hot, np.flatnonzero(np.diff(hot) > GRAM) + 1)
            cores = (r[of >= of.max() / 2] for r, of in ((r, excess[ids[r]]) for r in runs))
            found += [raw[c[0] : c[-1] + GRAM] for c in cores]
    return found


def trained(samples: list[bytes], size: int) -> bytes:
    """The last ``size`` bytes of a dictionary that zstandard trains on samples; all of them where they are too few."""
    whole = [s for s in samples if len(s) >= 8]
    try:
        return zstandard.train_dictionary(size + 1000, whole, k=SEGMENT, d=GRAM).as_bytes()[-size:]
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


class ToxicModel:
    """Two dictionaries and the regression; small enough to travel with every task."""

    def __init__(self, toxic: list[str], ordinary: list[str], share: float | None = None):
        bad, good = sorted({plain(t) for t in toxic}), sorted({plain(t) for t in ordinary})
        self.constant = None if bad and good else float(bool(bad))
        if self.constant is not None:
            return
        excess = significance(bad, good)
        self.ordinary = trained([w for t in good for w in windows(t)[:: WINDOW // STRIDE]], ORDINARY_BYTES)
        own = passages(bad, excess, max(SIGNIFICANT * excess.max(), 0.0)) or bad
        own = trained(own, TOXIC_BYTES)
        self.toxic = self.ordinary + own  # ordinary words cost the same under both
        self.marks = np.zeros(1 << BITS, dtype=bool)
        self.marks[gram_ids(own)] = True
        self.passing = np.full(len(THRESHOLDS), 1e-4)
        counts = [self.counts(t) for t in good]
        total = sum(n for n, _, _ in counts)
        self.passing = (sum(c for _, c, _ in counts) + 1) / (total + 2)
        x = np.array([self.of_counts(*c) for c in [*map(self.counts, bad), *counts]])
        self.regression = Logistic(x, np.array([1.0] * len(bad) + [0.0] * len(good)))
        if share is not None and 0 < share < 1:  # the sample takes as many of either class; the scores follow the true share
            self.regression.w[-1] += np.log(share / (1 - share)) - np.log(len(bad) / len(good))

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "tools"}

    def distances(self, raw: bytes) -> np.ndarray:
        if "tools" not in self.__dict__:
            self.tools = []
            for content in (self.ordinary, self.toxic):
                d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                d.precompute_compress(level=LEVEL)
                self.tools.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False).compress)
        one, two = self.tools
        out = np.zeros(max(0, -(-(max(1, len(raw) - WINDOW + STRIDE)) // STRIDE)) if len(raw) > 2 else 0, dtype=np.int64)
        # a window without a stretch of the toxic dictionary's own part has nothing that makes it shorter
        held = np.concatenate([[0], np.cumsum(self.marks[gram_ids(raw)])])
        first = np.arange(len(out)) * STRIDE
        last = np.minimum(first + WINDOW - GRAM + 1, len(held) - 1)
        for i in np.flatnonzero(held[last] > held[np.minimum(first, last)]).tolist():
            w = raw[i * STRIDE : i * STRIDE + WINDOW]
            out[i] = len(one(w)) - len(two(w))
        return out

    def counts(self, raw: bytes) -> tuple[int, np.ndarray, float]:
        d = self.distances(raw)
        return len(d), np.array([(d >= t).sum() for t in THRESHOLDS], dtype=float), float(d.max(initial=0))

    def of_counts(self, n: int, over: np.ndarray, most: float) -> np.ndarray:
        expected = n * self.passing
        return np.concatenate([(over - expected) / np.sqrt(expected + 1), np.sqrt(over / max(n, 1)), [most, np.log1p(n)]])

    def scores(self, texts: list[str]) -> np.ndarray:
        if self.constant is not None or not texts:
            return np.full(len(texts), self.constant or 0.0)
        return self.regression(np.array([self.of_counts(*self.counts(plain(t))) for t in texts]))


def train(docs: DataFrame, labels: DataFrame, most: int = MOST_TEXTS) -> ToxicModel:
    rows = texts_of(docs, labelled_ids(labels, "toxic", most)).orderBy("doc_id").collect()
    known = labels.filter(F.col("toxic").isin(0, 1) & (fold("doc_id", 5) != 0))
    share = known.agg(F.avg(F.col("toxic").cast("double"))).first()[0]
    return ToxicModel([r["text"] for r in rows if r["y"] == 1], [r["text"] for r in rows if r["y"] == 0], share)


def score_table(docs: DataFrame, model: ToxicModel) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of ``docs``."""
    scored = map_texts(docs, ("doc_id",), lambda texts: {"score": model.scores(texts)}, "score double")
    return scored.select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= DECIDE_AT).cast("int").alias("predicted"))


def kept(docs: DataFrame, model) -> DataFrame:
    """The rows that the filter keeps, with all their columns."""
    return filter_texts(docs, lambda texts: model.scores(texts) < DECIDE_AT)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score_table(docs, train(docs, table(spark, sf_dir, "labels")))
