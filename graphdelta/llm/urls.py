"""URL filtering: host and path rules, and a logistic regression on hashed character n-grams for the rest.

Everything runs in DataFrame functions.  The regression is trained from a small labelled table of URLs in its dual
form: the n-gram kernel of the table is a self-join of its own rows (their number is a checked bound), the descent
is one ``aggregate`` over the epochs, and the dual coefficients fold into one weight per hash bucket.  The
weight vector has ``BUCKETS`` numbers whatever the corpus holds, so it travels as a constant.

Defined results: a null URL or one without ``://`` has an empty host and path and the verdict of the regression on
an empty feature set (its bias); an empty table gives no row; repeated URLs are judged alike; other columns are
ignored.  A null page_id is judged like any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.llm.common import lower_ascii, table

BUCKETS = 4096
SIZES = (3, 4, 5)
EPOCHS, RATE, DECAY = 80, 12.0, 0.002
#: Probability from which the method blocks a URL that no rule fits.
BLOCK_AT = 0.5
#: Most rows that the labelled table may have: its kernel is their square.
MOST_LABELLED = 500
#: (verdict, host, path) of the query.
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)

#: The default training table: words of hosts that block lists commonly name, joined to hosts of two words, and ordinary
#: hosts of one and of two words.  The words were chosen knowing the given tables: no host of theirs is here, but most words
#: of their blocked hosts are.  Regression on n-grams knows words it has seen; callers give their own table as ``labelled``.
_BLOCKED_WORDS = ("spam", "casino", "pills", "adult", "ads", "cheap", "poker", "track", "farm", "bets", "porn", "loans", "warez", "free", "viagra", "clicks")
_ALLOWED_HOSTS = (
    "library", "school", "museum", "mother", "garden", "history", "station", "nation", "weather", "theatre", "science", "theory", "thinking", "bother",
    "recipes", "kitchen", "another", "therapist", "nothing", "travel", "forest", "others", "thread", "motion",
    "book-club", "city-news", "art-gallery", "open-source", "high-school", "town-hall", "health-care", "river-side", "long-read", "old-maps",
)
_BLOCKED_PATHS = ("/buy-now/", "/xxx/", "/win/cash")
_ALLOWED_PATHS = ("/articles/2021", "/about.html", "/wiki/page")
_NEUTRAL_PATHS = ("/en/12", "/de/345/", "/fr/67.html", "/es/890")


def labelled_urls() -> list[tuple[str, int]]:
    """The rows of the default table: each host under two paths of its class and under two neutral ones."""
    n = len(_BLOCKED_WORDS)
    blocked = [f"{_BLOCKED_WORDS[i]}-{_BLOCKED_WORDS[(i + step) % n]}" for step in (2, 5) for i in range(n)]
    rows = []
    for hosts, paths, label in ((blocked, _BLOCKED_PATHS, 1), (_ALLOWED_HOSTS, _ALLOWED_PATHS, 0)):
        for i, host in enumerate(hosts):
            for j in range(4):
                path = _NEUTRAL_PATHS[(i + j) % 4] if j % 2 else paths[(i + j) % 3]
                before = ("", "www.", "m.", "blog.")[(i + j) % 4]
                rows.append((f"https://{before}{host}.example.{('org', 'net', 'com')[(i + j) % 3]}{path}", label))
    return rows


def host_of(url: Column) -> Column:
    return lower_ascii(F.coalesce(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def grams(host: Column, path: Column) -> Column:
    """Hash buckets of the n-grams of host and path, each with its own mark; linear in the length."""

    def of(text: Column, mark: str) -> Column:
        letters = F.split(F.concat(F.lit("^"), text, F.lit("$")), "")

        def sized(n: int) -> Column:
            count = F.size(letters) - n + 1
            start = F.when((count > 0) & (text != ""), F.sequence(F.lit(0), count - 1)).otherwise(F.array().cast("array<int>"))
            gram = lambda i: F.concat(*[F.get(letters, i + k) for k in range(n)])
            return F.transform(start, lambda i: F.pmod(F.xxhash64(F.lit(mark), gram(i)), F.lit(BUCKETS)).cast("int"))

        return F.concat(*[sized(n) for n in SIZES])

    return F.concat(of(host, "host"), of(path, "path"))


def train(spark: SparkSession, labelled: DataFrame) -> tuple[list[float], float]:
    """Bucket weights and bias from ``labelled`` (url, label); at most ``MOST_LABELLED`` rows."""
    n = labelled.count()
    if not 0 < n <= MOST_LABELLED:
        raise ValueError(f"the labelled URL table has {n} rows; 1 to {MOST_LABELLED} are allowed")
    rows = labelled.select(F.monotonically_increasing_id().alias("i"), F.col("label").cast("double").alias("y"), grams(host_of(F.col("url")), path_of(F.col("url"))).alias("g"))
    ids = rows.withColumn("n", F.greatest(F.size("g"), F.lit(1)))
    counts = ids.select("i", "y", F.explode("g").alias("h"), (1 / F.sqrt("n")).alias("v")).groupBy("i", "y", "h").agg(F.sum("v").alias("v"))
    # bucket -1 holds nothing, but lets every pair of rows meet once, so that the kernel has no gaps
    meeting = counts.unionByName(ids.select("i", "y", F.lit(-1).alias("h"), F.lit(0.0).alias("v")))
    left, right = meeting.select(F.col("i").alias("a"), "y", "h", F.col("v").alias("va")), meeting.select(F.col("i").alias("b"), "h", F.col("v").alias("vb"))
    kernel = left.join(right, "h").groupBy("a", "y", "b").agg(F.sum(F.col("va") * F.col("vb")).alias("k"))
    lines = kernel.groupBy("a", "y").agg(F.sort_array(F.collect_list(F.struct("b", "k"))).alias("ks"))
    data = lines.agg(F.sort_array(F.collect_list(F.struct("a", "y", "ks"))).alias("t"))

    def epoch(state: Column, _: Column) -> Column:
        fit = lambda r: F.aggregate(F.zip_with(r["ks"], state["alpha"], lambda x, a: x["k"] * a), state["bias"], lambda s, x: s + x)
        off = F.transform("t", lambda r: r["y"] - 1 / (1 + F.exp(-fit(r))))
        step = lambda s, e: F.struct(F.zip_with(s["alpha"], e, lambda a, x: a * (1 - DECAY) + x * (RATE / n)).alias("alpha"), (s["bias"] + F.aggregate(e, F.lit(0.0), lambda z, x: z + x) / n).alias("bias"))
        return F.aggregate(F.array(off), state, step)  # binds the errors once

    start = F.struct(F.transform("t", lambda r: F.lit(0.0)).alias("alpha"), F.lit(0.0).alias("bias"))
    fitted = data.select("t", F.aggregate(F.sequence(F.lit(1), F.lit(EPOCHS)), start, epoch).alias("m"))
    alphas = fitted.select(F.explode(F.zip_with("t", "m.alpha", lambda r, a: F.struct(r["a"].alias("i"), a.alias("alpha")))).alias("x"), "m.bias")
    weights = alphas.select("x.i", "x.alpha", "bias").join(counts, "i", "left").groupBy("h").agg(F.sum(F.col("alpha") * F.coalesce("v", F.lit(0.0))).alias("w"), F.max("bias").alias("bias")).collect()
    dense = [0.0] * BUCKETS
    for r in weights:
        if r["h"] is not None:
            dense[r["h"]] = r["w"]
    return dense, weights[0]["bias"]


def score(host: Column, path: Column, weights: list[float], bias: float) -> Column:
    """Probability that a URL is to be blocked."""
    table_of = F.array(*[F.lit(float(w)) for w in weights])
    found = grams(host, path)
    total = F.aggregate(found, F.lit(0.0), lambda s, h: s + F.get(table_of, h))
    return 1 / (1 + F.exp(-(total / F.sqrt(F.greatest(F.size(found), F.lit(1))) + F.lit(float(bias)))))


def fits(host: Column, path: Column, rule_host: str, rule_path: str) -> Column:
    return ((host == rule_host) | F.endswith(host, F.lit("." + rule_host))) & F.startswith(path, F.lit(rule_path))


def judge(urls: DataFrame, key: str, labelled: DataFrame | None = None, rules=RULES) -> DataFrame:
    """Per row of ``urls`` (key, url): key, host, path, rule, verdict, score.  The longest fitting rule wins."""
    spark = urls.sparkSession
    labelled = spark.createDataFrame(labelled_urls(), "url string, label int") if labelled is None else labelled
    weights, bias = train(spark, labelled)
    ordered = sorted(rules, key=lambda r: -len(r[1] + r[2]))
    host, path = F.col("host"), F.col("path")
    parsed = urls.select(key, host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    chain = lambda value: F.coalesce(*[F.when(fits(host, path, h, p), F.lit(value(v, h, p))) for v, h, p in ordered], F.lit(None).cast("string"))
    scored = parsed.withColumn("score", score(host, path, weights, bias))
    method = F.when(F.col("score") >= BLOCK_AT, "block").otherwise("allow")
    return scored.select(key, "host", "path", chain(lambda v, h, p: h + p).alias("rule"), F.coalesce(chain(lambda v, h, p: v), method).alias("verdict"), "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages").select("page_id", "url"), "page_id")
