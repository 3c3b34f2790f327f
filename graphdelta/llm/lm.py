"""Log-bilinear language model, trained by noise-contrastive estimation and scored with exact normalisation.

Token counts cover the whole training side.  The model has two levels.  Its classes are the end, the most frequent
words, the endings that most tokens of the other words have, and one class for what is left; a word has its smoothed share of its
class, and any word, seen or not, has a class, as target and as context.  A context is the two tokens before; its
prediction is a weighted sum of their vectors, and a batched matrix product over the distinct contexts of a run of texts
gives every class's score and so the normalised log-probabilities.

Training tells a token from tokens drawn by frequency.  It starts from a small fixed number of texts; then every
partition of the training side goes on over all its texts, and the parameters are averaged by tokens seen, which
only moves one row per parameter and task.  Counts of the ``LOCAL`` most frequent tokens travel with the tasks; the
counts of all rarer ones meet their texts in a join on the token.

Defined results: null and blank texts consist of the end token only; a text of any length is scored whole; equal texts
get equal scores up to rounding; with no training text the counts are zero and the model is uniform; an empty table
gives no row; extra columns are ignored.
"""

from __future__ import annotations

from itertools import repeat

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.llm.common import WORD_GAP, fold, lower_ascii, map_texts, ready, runs, saved, table
from graphdelta.llm.learning import texts_of

#: Classes of the model: the shared one, the end, ``NAMED`` words, and endings of ``TAIL`` bytes.
CLASSES, WIDTH = 512, 16
NAMED, TAIL = 126, 2
OTHER, END = 0, 1
#: Rarer words, up to this many, whose counts travel with the tasks as well.
LOCAL = 1 << 18
#: Texts of the first training, and its passes.
FIRST_TEXTS, FIRST_PASSES = 400, 12
STEP_TOKENS, NOISE, RATE = 16_384, 48, 0.15


def counts_of(docs: DataFrame) -> DataFrame:
    """(token, c) of every word of ``docs``; map-side sums come first."""
    split = docs.select(F.explode(F.split(lower_ascii(F.col("text")), WORD_GAP)).alias("token"))
    return split.filter(F.col("token") != "").groupBy("token").agg(F.count(F.lit(1)).alias("c"))


def cut(text: str) -> list[bytes]:
    return text.encode().lower().split()


class Lexicon:
    """Places of the frequent words, their counts, the classes of all words, and the totals of the training side."""

    def __init__(self, words: list[str], counts: list[int], ends: int, total: int, distinct: int, endings: list[tuple[bytes, int, int]] = ()):
        """``endings`` are (ending, tokens, words) over all words of the training side."""
        self.index = {w.encode(): i for i, w in enumerate(words)}
        self.missing = len(words)
        self.logs = np.log10(np.array([*counts, 0], dtype=float) + 1)
        self.named = min(len(words), NAMED)
        self.ends, self.total, self.distinct = ends, total + ends, distinct + (ends > 0)
        tails = {e: [n, d] for e, n, d in endings}
        for w, c in zip(list(self.index)[: self.named], counts, strict=False):
            if (tail := tails.get(w[-TAIL:])) is not None:
                tail[0] -= c
                tail[1] -= 1
        chosen = sorted(((e, n, d) for e, (n, d) in tails.items() if n > 0), key=lambda t: (-t[1], t[0]))[: CLASSES - 2 - self.named]
        first = 2 + self.named
        self.endings = {e: first + i for i, (e, _, _) in enumerate(chosen)}
        # tokens and words of the classes that hold several words
        mass, size = np.zeros(CLASSES), np.zeros(CLASSES)
        mass[first : first + len(chosen)], size[first : first + len(chosen)] = [n for _, n, _ in chosen], [d for _, _, d in chosen]
        mass[OTHER], size[OTHER] = total - sum(counts[: self.named]) - mass.sum(), distinct - self.named - size.sum()
        self.inside = np.log10(mass + size + 1)  # smoothed, with one unseen word
        share = np.full(CLASSES, 0.5)
        share[END] += ends
        share[2:first] += counts[: self.named]
        share += mass
        self.share = share / share.sum()
        self.kinds = np.array([*range(2, first), *(self.endings.get(w[-TAIL:], OTHER) for w in list(self.index)[self.named :]), OTHER], dtype=np.int64)

    def places(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.index.get, words, repeat(self.missing)), dtype=np.int64, count=len(words))

    def classes(self, words: list[bytes], places: np.ndarray) -> np.ndarray:
        """Classes of a text's tokens, the end last."""
        out = np.append(self.kinds[places], END)
        for i in np.flatnonzero(places == self.missing):
            out[i] = self.endings.get(words[i][-TAIL:], OTHER)
        return out


def contexts(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Target, last and last but one class at every token; ends stand before a text."""
    target = np.concatenate(texts)
    one = np.concatenate([np.append(END, t[:-1]) for t in texts])
    two = np.concatenate([np.append([END, END], t)[: len(t)] for t in texts])
    return target, one, two


class LogBilinear:
    """Parameters: context vectors, target vectors, weights of the two places, biases."""

    def __init__(self, share: np.ndarray):
        rng = np.random.default_rng(11)
        self.noise = share
        self.r = rng.normal(0, 0.1, (CLASSES, WIDTH))
        self.q = rng.normal(0, 0.1, (CLASSES, WIDTH))
        self.c = np.array([np.full(WIDTH, 1.0), np.full(WIDTH, 0.5)])
        self.b = np.log(share)
        self.seen = [np.full_like(x, 0.05) for x in (self.r, self.q, self.c, self.b)]
        self.rng = rng

    def flat(self) -> np.ndarray:
        return np.concatenate([x.ravel() for x in (self.r, self.q, self.c, self.b)])

    def load(self, values: np.ndarray) -> None:
        at = 0
        for x in (self.r, self.q, self.c, self.b):
            x[...] = values[at : at + x.size].reshape(x.shape)
            at += x.size

    def predict(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        return self.r[one] * self.c[0] + self.r[two] * self.c[1]

    def step(self, target: np.ndarray, one: np.ndarray, two: np.ndarray) -> None:
        """One noise-contrastive step: the same drawn tokens serve every context of the step."""
        drawn = self.rng.choice(CLASSES, size=NOISE, p=self.noise)
        p = self.predict(one, two)
        odds = np.log(NOISE * self.noise)
        true = 1 / (1 + np.exp(-np.clip(np.einsum("ij,ij->i", p, self.q[target]) + self.b[target] - odds[target], -30, 30))) - 1
        false = 1 / (1 + np.exp(-np.clip(p @ self.q[drawn].T + self.b[drawn] - odds[drawn], -30, 30)))
        n = len(target)
        to_p = (true[:, None] * self.q[target] + false @ self.q[drawn]) / n
        gq, gb, gr = np.zeros_like(self.q), np.zeros_like(self.b), np.zeros_like(self.r)
        for k in range(WIDTH):
            gq[:, k] = np.bincount(target, weights=true * p[:, k], minlength=CLASSES) / n
            gr[:, k] = np.bincount(one, weights=to_p[:, k] * self.c[0, k], minlength=CLASSES) + np.bincount(two, weights=to_p[:, k] * self.c[1, k], minlength=CLASSES)
        gb += np.bincount(target, weights=true, minlength=CLASSES) / n
        np.add.at(gq, drawn, false.T @ p / n)
        np.add.at(gb, drawn, false.sum(0) / n)
        gc = np.array([(to_p * self.r[one]).sum(0), (to_p * self.r[two]).sum(0)])
        for x, g, s in zip((self.r, self.q, self.c, self.b), (gr, gq, gc, gb), self.seen, strict=True):
            s += g * g * n
            x -= RATE * g * np.sqrt(n) / np.sqrt(s)

    def learn(self, texts: list[np.ndarray]) -> None:
        target, one, two = contexts(texts)
        for at in range(0, len(target), STEP_TOKENS):
            self.step(target[at : at + STEP_TOKENS], one[at : at + STEP_TOKENS], two[at : at + STEP_TOKENS])

    def log10(self, texts: list[np.ndarray]) -> list[float]:
        """Normalised log10 probability of every text's classes."""
        target, one, two = contexts(texts)
        keys, place = np.unique(one * CLASSES + two, return_inverse=True)
        out = np.empty(len(target))
        order = np.argsort(place, kind="stable")
        bounds = np.searchsorted(place[order], np.arange(0, len(keys) + 2048, 2048))
        q, b = self.q.astype(np.float32).T, self.b.astype(np.float32)
        for i, at in enumerate(range(0, len(keys), 2048)):
            some = keys[at : at + 2048]
            scores = self.predict(some // CLASSES, some % CLASSES).astype(np.float32) @ q + b
            top = scores.max(1)
            norm = top + np.log(np.exp(scores - top[:, None]).sum(1))
            mine = order[bounds[i] : bounds[i + 1]]
            row = place[mine] - at
            out[mine] = scores[row, target[mine]] - norm[row]
        ends = np.cumsum([len(t) for t in texts])
        return (np.add.reduceat(out, np.append(0, ends[:-1])) / np.log(10)).tolist()


def lexicon(counts: DataFrame, ends: int) -> Lexicon:
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    # the least count whose words, with all more frequent ones, fit: a few hundred steps, whatever the corpus holds
    step = F.floor(F.log2(F.col("c").cast("double")) * 8)
    held, least = 0, None
    for r in sorted(counts.groupBy(step.alias("s")).agg(F.count(F.lit(1)).alias("n"), F.min("c").alias("low")).collect(), key=lambda r: -r["s"]):
        held += r["n"]
        if held > LOCAL:
            break
        least = r["low"]
    top = counts.filter(F.col("c") >= F.lit(least) if least else F.lit(False)).toPandas().sort_values(["c", "token"], ascending=[False, True])
    tail = F.substring(F.col("token").cast("binary"), -TAIL, TAIL)
    endings = counts.groupBy(tail.alias("e")).agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("d")).collect()  # 256 ** TAIL at most
    return Lexicon(top["token"].tolist(), top["c"].tolist(), ends, int(total), int(distinct), [(bytes(r["e"]), r["n"], r["d"]) for r in endings])


def train(docs: DataFrame, lex: Lexicon) -> LogBilinear:
    """Train over all texts of ``docs``."""
    ready(docs.sparkSession)
    model = LogBilinear(lex.share)
    ids = docs.filter(F.col("doc_id").isNotNull()).select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(FIRST_TEXTS).distinct()
    first = texts_of(docs, ids).orderBy("doc_id").collect()
    sample = [lex.classes(words, lex.places(words)) for words in (cut(r["text"] or "") for r in first)]
    if not sample:
        return model
    for _ in range(FIRST_PASSES):
        model.learn(sample)
    shared = docs.sparkSession.sparkContext.broadcast((lex, model))

    def work(batches):
        import pyarrow as pa

        words, mine = shared.value
        start, tokens = mine.flat(), 0
        for batch in batches:
            for texts in runs(batch.column("text").to_pylist()):
                seqs = [words.classes(c, words.places(c)) for c in map(cut, texts)]
                mine.learn(seqs)
                tokens += sum(map(len, seqs))
        if tokens:
            values = mine.flat()
            mine.load(start)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(values), dtype=np.int32)), pa.array(values * tokens), pa.array(np.full(len(values), float(tokens)))], names=["i", "v", "n"])

    parts = docs.select("text").mapInArrow(work, "i int, v double, n double")
    rows = parts.groupBy("i").agg((F.sum("v") / F.sum("n")).alias("v")).orderBy("i").toPandas()
    model.load(rows["v"].to_numpy())
    return model


def score(docs: DataFrame, modulus: int = 7, held: int = 2) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    spark = docs.sparkSession
    ready(spark)
    taught = docs.filter(fold("doc_id", modulus) != held).select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    counts = saved(counts_of(taught), "counts")
    lex = lexicon(counts, taught.count())
    model = train(taught, lex)
    shared = spark.sparkContext.broadcast((lex, model))

    def make(texts: list[str]) -> dict:
        words, net = shared.value
        cuts = [cut(t) for t in texts]
        places = [words.places(c) for c in cuts]
        classes = [words.classes(c, p) for c, p in zip(cuts, places, strict=True)]
        named, other = [], []
        for p in places:
            logs = words.logs[p]
            named.append(float(logs[p < words.named].sum()) + float(np.log10(words.ends + 1)))
            other.append(float(logs[p >= words.named].sum()))
        return {
            "n_tokens": [len(c) for c in classes],
            "n_local": [int((p < words.missing).sum()) + (words.ends > 0) for p in places],
            "named": named,
            "other": other,
            "net": net.log10(classes),
            "inside": [float(words.inside[c[(c == OTHER) | (c >= 2 + words.named)]].sum()) for c in classes],
            "rest": [[c[i].decode() for i in np.flatnonzero(p == words.missing)] for c, p in zip(cuts, places, strict=True)],
        }

    added = "n_tokens long, n_local long, named double, other double, net double, inside double, rest array<string>"
    seen = saved(map_texts(docs, ("doc_id",), make, added).withColumn("row", F.monotonically_increasing_id()), "seen")
    rest = seen.select("row", F.explode("rest").alias("token"))
    found = rest.join(counts, "token").groupBy("row").agg(F.sum(F.log10(F.col("c") + 1)).alias("far"), F.count(F.lit(1)).alias("n_far"))
    far, n_far = F.coalesce("far", F.lit(0.0)), F.coalesce("n_far", F.lit(0))
    whole = float(np.log10(lex.total + lex.distinct + 1))
    return seen.drop("rest").join(found, "row", "left").select(
        "doc_id",
        (fold("doc_id", modulus) == held).alias("held_out"),
        "n_tokens",
        (F.col("n_local") + n_far).alias("n_known"),
        F.lit(lex.total).cast("long").alias("train_tokens"),
        (F.col("named") + F.col("other") + far - F.col("n_tokens") * whole).alias("base_score"),
        (F.col("net") + F.col("other") + far - F.col("inside")).alias("score"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"))
