"""What the learned filters share: bounded labelled samples and a small logistic regression."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.llm.common import fold


def labelled_ids(labels: DataFrame, column: str, most: int, modulus: int = 5) -> DataFrame:
    """doc_id and y of at most ``most`` rows of each class outside fold 0, chosen by a hash of the id."""
    known = labels.filter(F.col("doc_id").isNotNull() & F.col(column).isin(0, 1) & (fold("doc_id", modulus) != 0)).groupBy("doc_id").agg(F.max(F.col(column).cast("int")).alias("y"))
    one = lambda y: known.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    return one(1).unionByName(one(0))


def texts_of(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Texts of a bounded set of ids; only the ids travel."""
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(ids), "doc_id")


class Logistic:
    """L2 logistic regression by Newton steps over standardised columns."""

    def __init__(self, x: np.ndarray, y: np.ndarray, decay: float = 1.0, steps: int = 30):
        self.mean, self.scale = x.mean(0), x.std(0) + 1e-9
        z = self.grown(x)
        w = np.zeros(z.shape[1])
        penalty = np.full(len(w), decay)
        penalty[-1] = 1e-3
        for _ in range(steps):
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            slope = z.T @ (p - y) + penalty * w
            bend = (z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty)
            step = np.linalg.solve(bend, slope)
            w -= step * min(1.0, 4.0 / (np.abs(step).max() + 1e-12))
            if np.abs(step).max() < 1e-6:
                break
        self.w = w

    def grown(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        return np.hstack([z, np.ones((len(z), 1))])

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.grown(x) @ self.w, -30, 30)))
