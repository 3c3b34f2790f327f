"""Operators over whole tables: language model, vectors, components, pipeline."""

import collections
import zlib

import numpy as np

from graphdelta.llm import lm, neighbours
from graphdelta.llm.components import components


def test_components(spark):
    pairs = [(1, 2), (2, 3), (9, 8), (8, 7), (7, 3), (20, 21), (5, 5), (21, 20)]
    got = {r["id"]: r["component"] for r in components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 7: 1, 8: 1, 9: 1, 20: 20, 21: 20}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_base_scores_and_normalisation(spark, docs):
    texts = [None, "", "The cat. the CAT", "cat the dog " * 40, *(f"the w{i} cat" for i in range(40))]
    rows = {r["doc_id"]: r for r in lm.score(docs(texts)).collect()}
    words = [[*(t or "").encode().lower().split(), "END"] for t in texts]
    c = collections.Counter(w for i, ws in enumerate(words) if zlib.crc32(str(i).encode()) % 7 != 2 for w in ws)
    total, distinct = sum(c.values()), len(c)
    for i, ws in enumerate(words):
        r = rows[i]
        assert r["held_out"] == (zlib.crc32(str(i).encode()) % 7 == 2)
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(ws), sum(c[w] > 0 for w in ws), total)
        assert abs(r["base_score"] - sum(np.log10((c[w] + 1) / (total + distinct + 1)) for w in ws)) < 1e-6
        assert r["score"] < 0
    lex = lm.Lexicon(["a", "b"], [5, 2], 3, 9, 4)
    net = lm.LogBilinear(lex.share)
    each = [net.log10([np.array([k, lm.END])])[0] - net.log10([np.array([k, lm.END])])[0] + 10 ** (net.log10([np.array([k])])[0]) for k in range(lm.CLASSES)]
    assert abs(sum(each) - 1) < 1e-4
    assert lm.score(docs([])).count() == 0


def test_every_word_has_a_class_and_shares_sum_to_one():
    counts = collections.Counter({f"w{i}{'abcd'[i % 4]}x": 1 + 900 // (i + 1) for i in range(600)} | {"é": 7, "z": 3})
    order = sorted(counts, key=lambda w: (-counts[w], w))
    tails = collections.Counter(w.encode()[-lm.TAIL :] for w in order)
    tokens = collections.Counter()
    for w in order:
        tokens[w.encode()[-lm.TAIL :]] += counts[w]
    local = order[:300]  # the others are looked up by their ending alone
    lex = lm.Lexicon(local, [counts[w] for w in local], 5, sum(counts.values()), len(order), [(e, tokens[e], d) for e, d in tails.items()])
    words = [w.encode() for w in order]
    kinds = lex.classes(words, lex.places(words))
    assert kinds[-1] == lm.END and len(set(kinds[: lm.NAMED])) == lm.NAMED and len(set(kinds[lm.NAMED : -1])) == 6
    for kind in set(kinds[lm.NAMED : -1]):
        inside = [counts[w] + 1 for w, k in zip(order, kinds, strict=False) if k == kind]
        assert abs((sum(inside) + 1) / 10 ** lex.inside[kind] - 1) < 1e-9
    odd = [b"never", b"x" * 9, b"q"]
    assert all(k == lm.OTHER or k in lex.endings.values() for k in lex.classes(odd, lex.places(odd))[:-1])


def test_near_vectors_equal_brute_force(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(300, 16))
    base = rng.normal(size=16)
    x[:60] = base + rng.normal(scale=0.05, size=(60, 16))
    x[60:64] = x[100]
    rows = [(i, [float(v) for v in np.float32(r)], 0) for i, r in enumerate(x)]
    odd = [(1000, None, 0), (1001, [0.0] * 16, 0), (1002, [float("nan")] * 16, 0), (1003, [1.0] * 15 + [None], 0), (1004, [], 0), (1005, [1.0, 2.0], 0), (None, [1.0] * 16, 0)]
    table = spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>, label int")
    got = {r["vec_id"]: r for r in neighbours.near_copies(table.select("vec_id", "embedding")).collect()}
    v = np.array([r[1] for r in rows])
    v /= np.linalg.norm(v, axis=1)[:, None]
    near = v @ v.T >= 0.95
    np.fill_diagonal(near, False)
    found = sum(got[i]["n_links"] for i in range(300))
    assert found >= 0.9 * near.sum() and all(got[i]["n_links"] <= near[i].sum() for i in range(300))
    assert all(got[i]["component_id"] == i and got[i]["n_links"] == 0 and got[i]["kept"] for i in range(1000, 1006))
    assert not got[None]["kept"]
    assert neighbours.near_copies(table.select("vec_id", "embedding").limit(0)).count() == 0


def groups_with_bridges(dims=32):
    """Two tight groups of 20 distinct vectors; every vector's eight nearest lie in its own group, all links cross."""
    rng = np.random.default_rng(2)
    angle = np.arccos(0.965)
    near = np.eye(dims)[0]
    far = np.cos(angle) * np.eye(dims)[0] + np.sin(angle) * np.eye(dims)[1]
    return np.concatenate([c + rng.normal(0, 0.002, (20, dims)) for c in (near, far)])


def test_links_behind_nearer_neighbours_are_found(spark):
    x = groups_with_bridges()
    s = (x / np.linalg.norm(x, axis=1)[:, None]) @ (x / np.linalg.norm(x, axis=1)[:, None]).T
    assert (s >= neighbours.THRESHOLD).all()
    assert all((np.argsort(-s[i])[:9] // 20 == i // 20).all() for i in range(40))
    table = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = neighbours.near_copies(table).collect()
    assert {(r["n_links"], r["component_id"]) for r in got} == {(39, 0)}
    assert [r["vec_id"] for r in got if r["kept"]] == [0]


def test_all_rows_are_compared_when_the_audit_stays_low(spark, monkeypatch):
    monkeypatch.setattr(neighbours, "audit", lambda *_: 0.0)
    monkeypatch.setattr(neighbours, "exact", lambda reps, lists, threshold: lists.select("a", "b").limit(0))
    monkeypatch.setattr(neighbours, "saturated", lambda lists, threshold: lists.select(lists.a.alias("id")).limit(0))
    monkeypatch.setattr(neighbours, "MOST_ROUNDS", 2)
    table = spark.createDataFrame([(1, [1.0, 0.0]), (2, [1.0, 0.01]), (3, [0.0, 1.0]), (4, [1.0, -0.01])], "vec_id long, embedding array<double>")
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in neighbours.near_copies(table).collect()}
    assert got == {1: (2, 1), 2: (2, 1), 3: (0, 3), 4: (2, 1)}
