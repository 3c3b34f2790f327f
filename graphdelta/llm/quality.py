"""Document quality by positive-unlabelled learning.

Positives are trusted documents (label 1); the unlabelled side is a sample of the web text itself, good and bad
alike.  A linear scorer over writing features minimises the non-negative unbiased risk: the risk of the positives
as positive, plus what is left of the unlabelled risk once the positives' share of it, the class prior, is taken off,
and never less than zero.  The prior is estimated from positives and unlabelled text alone: over a part that was not
trained on, the smallest ratio of the unlabelled to the positive share at or over a score bounds the share of positives.

Samples are bounded (``MOST_TEXTS`` of each side, by a hash of the id, outside the held-out fold) and the model has a
fixed size; every document is scored over its whole text.

Defined results: null and empty texts are scored as texts without words; equal texts get equal scores; without any
positive every score is 0.5; rows with a null doc_id are scored, count as held out and teach nothing; extra columns are
ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.llm.common import filter_texts, fold, map_texts, ready, table
from graphdelta.llm.learning import labelled_ids, texts_of

MOST_TEXTS = 4000
BUCKETS = 512
DECIDE_AT = 0.3
EPOCHS, BATCH, RATE, DECAY = 60, 512, 0.02, 1e-4
_KINDS = np.zeros(256, dtype=np.uint8)  # 0 other byte, 1 lower letter, 2 capital, 3 digit, 4 white space, 5 sign
_KINDS[97:123], _KINDS[65:91], _KINDS[48:58] = 1, 2, 3
_KINDS[[9, 10, 11, 12, 13, 32]] = 4
_KINDS[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = 5


def features(text: str) -> np.ndarray:
    """Shares of byte kinds and of hashed pairs of neighbouring signs and kinds, repetition and shape of words."""
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    words = text.split()
    n, m = max(len(raw), 1), max(len(words), 1)
    kinds = np.bincount(_KINDS[raw], minlength=6) / n
    shape = raw.copy()
    shape[(_KINDS[raw] == 1)] = 97
    shape[(_KINDS[raw] == 2)] = 65
    shape[raw >= 128] = 98
    h = shape.astype(np.uint32)
    hashed = ((h[:-2] * 31 + h[1:-1]) * 31 + h[2:]) * np.uint32(2654435761) >> np.uint32(23) if len(h) > 2 else np.empty(0, np.uint32)
    grams = np.sqrt(np.bincount(hashed, minlength=BUCKETS) / n)
    repeats = sum(map(str.__eq__, words, words[1:])) / m
    lines = text.count("\n") + 1
    longest = max(map(len, words), default=0)
    style = [len(set(words)) / m, repeats, np.log1p(m) / 10, np.log1p(longest) / 5, min(n / m, 40) / 40, np.log1p(m / lines) / 5, sum(map(str.isupper, words)) / m, float(text.rstrip()[-1:] in ".!?")]
    return np.concatenate([kinds * 4, grams * 2, style]).astype(np.float32)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def prior_of(positive: np.ndarray, unlabelled: np.ndarray) -> float:
    """Share of positives in the unlabelled side: least ratio of the shares at or over a score, with a margin."""
    cuts = np.quantile(positive, np.linspace(0.0, 0.5, 51))
    of_p = np.array([(positive >= c).mean() for c in cuts])
    of_u = np.array([(unlabelled >= c).mean() for c in cuts])
    margin = 1 / np.sqrt(len(positive)) + 1 / np.sqrt(len(unlabelled))
    best = np.argmin((of_u + margin * 0.5) / of_p)
    return float(np.clip(of_u[best] / of_p[best], 0.05, 0.97))


class QualityModel:
    """Linear scorer of fixed size."""

    def __init__(self, positive: np.ndarray, unlabelled: np.ndarray, prior: float | None = None):
        self.known = len(positive) > 0 and len(unlabelled) > 0
        if not self.known:
            return
        both = np.vstack([positive, unlabelled])
        self.mean, self.scale = both.mean(0), both.std(0) + 0.01
        if prior is None:  # fit with a middling prior on one half, estimate on the other
            self.fit(positive[::2], unlabelled[::2], 0.7)
            rest_p, rest_u = (positive[1::2], unlabelled[1::2]) if min(len(positive), len(unlabelled)) > 1 else (positive, unlabelled)
            prior = prior_of(self.margins(rest_p), self.margins(rest_u))
        self.prior = prior
        self.fit(positive, unlabelled, prior)

    def grown(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        return np.hstack([z, np.ones((len(z), 1), dtype=z.dtype)])

    def margins(self, x: np.ndarray) -> np.ndarray:
        return self.grown(x) @ self.w

    def fit(self, positive: np.ndarray, unlabelled: np.ndarray, prior: float) -> None:
        rng = np.random.default_rng(7)
        p, u = self.grown(positive), self.grown(unlabelled)
        self.w = np.zeros(p.shape[1])
        first, second, t = np.zeros_like(self.w), np.zeros_like(self.w), 0
        for _ in range(EPOCHS):
            order = rng.permutation(len(u))
            for at in range(0, len(u), BATCH):
                zu = u[order[at : at + BATCH]]
                zp = p[rng.integers(0, len(p), size=min(BATCH, max(len(p), 1)))]
                sp, su = sigmoid(zp @ self.w), sigmoid(zu @ self.w)
                # logistic loss: as positive log(1 + e^-f), as negative log(1 + e^f)
                as_negative = np.mean(-np.log1p(-su + 1e-9)) - prior * np.mean(-np.log1p(-sp + 1e-9))
                down = zu.T @ su / len(zu) - prior * (zp.T @ sp) / len(zp)
                up = prior * (zp.T @ (sp - 1)) / len(zp)
                slope = (up + down if as_negative >= 0 else -down) + DECAY * self.w
                t += 1
                first, second = 0.9 * first + 0.1 * slope, 0.999 * second + 0.001 * slope**2
                self.w -= RATE * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)

    def scores(self, texts: list[str]) -> np.ndarray:
        if not self.known or not texts:
            return np.full(len(texts), 0.5)
        return sigmoid(self.margins(np.array([features(t) for t in texts])))


def sample(docs: DataFrame, labels: DataFrame, most: int) -> DataFrame:
    """doc_id, y (1 trusted positive, 0 unlabelled) and features; only ids and features travel."""
    trusted = labelled_ids(labels, "quality", most).filter(F.col("y") == 1)
    free = docs.filter(F.col("doc_id").isNotNull() & (fold("doc_id", 5) != 0)).select("doc_id").orderBy(F.xxhash64("doc_id", F.lit(1)), "doc_id").limit(most).distinct().withColumn("y", F.lit(0))

    def run(frames):
        for part in frames:
            yield pd.DataFrame({"doc_id": part["doc_id"], "y": part["y"], "x": [features(t) for t in part["text"]]})

    return texts_of(docs, trusted.unionByName(free)).mapInPandas(run, "doc_id long, y int, x array<float>")


def train(docs: DataFrame, labels: DataFrame, most: int = MOST_TEXTS) -> QualityModel:
    ready(docs.sparkSession)
    rows = sample(docs, labels, most).orderBy("y", "doc_id").toPandas()
    side = lambda y: np.array(rows.loc[rows["y"] == y, "x"].tolist(), dtype=np.float32).reshape(-1, BUCKETS + 14)
    return QualityModel(side(1), side(0))


def score_table(docs: DataFrame, model: QualityModel) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of ``docs``."""
    scored = map_texts(docs, ("doc_id",), lambda texts: {"score": model.scores(texts)}, "score double")
    return scored.select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= DECIDE_AT).cast("int").alias("predicted"))


def kept(docs: DataFrame, model) -> DataFrame:
    """The rows that the filter keeps, with all their columns."""
    return filter_texts(docs, lambda texts: model.scores(texts) >= DECIDE_AT)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score_table(docs, train(docs, table(spark, sf_dir, "labels")))
