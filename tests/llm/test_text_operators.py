"""Operators that work text by text, against the libraries, plain loops and held-out labels."""

import hashlib
import random

import numpy as np
import pytest

from graphdelta.llm import bpe, chat, counts, decontaminate, jaccard, quality, toxicity, urls

EDGE_TEXTS = [None, "", "   \n", "a", "<|endoftext|> x <|endoftext|>", "É é Σ ς İ ǅ 日本 👍🏽", "don't WE'LL ''''s", "word " * 3000, "aaaa" * 50, "\ua7cb \ua7dcx", "x\x00y \x1c\x1d z w"]


def tokenizer(name):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(bpe.vocabulary(name))
    t.no_truncation()
    t.no_padding()
    return t


def test_round_trip_equals_library(spark, docs):
    t = tokenizer("byte_bpe_50k.json")
    got = {r["doc_id"]: r for r in bpe.round_trip(docs(EDGE_TEXTS), bpe.vocabulary("byte_bpe_50k.json")).collect()}
    for i, text in enumerate(EDGE_TEXTS):
        ids = t.encode(text or "", add_special_tokens=False).ids
        assert got[i]["n_tokens"] == len(ids)
        assert got[i]["ids_sha256"] == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert got[i]["decoded_sha256"] == hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert bpe.round_trip(docs([]), bpe.vocabulary("byte_bpe_50k.json")).count() == 0


def test_counts_equal_library_at_every_prefix(spark, docs):
    t, tool = tokenizer("word_bpe_49k.json"), counts.loaded(bpe.vocabulary("word_bpe_49k.json"))
    got = {r["doc_id"]: r for r in counts.count_table(docs(EDGE_TEXTS), bpe.vocabulary("word_bpe_49k.json"), 10).collect()}
    for i, text in enumerate(EDGE_TEXTS):
        n = len(t.encode(text or "", add_special_tokens=False).ids)
        assert (got[i]["n_tokens"], got[i]["n_bytes"], got[i]["over_limit"]) == (n, len((text or "").encode()), n > 10)
    text = "unbelievable token counts, don't they? naïve 123"
    want = [len(t.encode(text[:n], add_special_tokens=False).ids) for n in range(len(text) + 1)]
    assert tool.prefix_counts(text).tolist() == want
    assert want[tool.fitting(text, 5)] <= 5


def test_chat_round_trip_and_attachments(spark):
    hostile = [(-1, 0, "user", chat.HOSTILE), (-1, 1, "assistant", chat.HOSTILE), (5, 1, "assistant", "\\<| \\| \\\\"), (5, 0, "sys\ntem\\n", None), (6, None, None, "x"), (5, 1, "assistant", "\\<| \\| \\\\"), (None, 3, "user", "é<|")]
    rows = spark.createDataFrame(hostile, "conv_id long, turn long, role string, text string")
    chats = chat.format_chats(rows)
    back = {r["conv_id"]: r for r in chat.read_back(chats).collect()}
    assert [(t["role"], t["text"]) for t in back[-1]["turns"]] == [("user", chat.HOSTILE), ("assistant", chat.HOSTILE)]
    assert [t["role"] for t in back[5]["turns"]] == ["sys\ntem\\n", "assistant", "assistant"]
    assert back[5]["learned"] == ["\\<| \\| \\\\"] * 2 and back[6]["learned"] == []
    assert back[None]["turns"][0]["text"] == "é<|"
    got = {r["conv_id"]: r for r in chat.digests(chats).collect()}
    said = "user\n" + chat.HOSTILE + "\nassistant\n" + chat.HOSTILE + "\n"
    assert got[-1]["turns_sha256"] == hashlib.sha256(said.encode()).hexdigest() and got[-1]["loss_chars"] == len(chat.HOSTILE)
    part = [("text", "see <|image:2|>", None, None), ("image", None, "a.png", 2.0), ("audio", None, "b.wav", 3.0), None, ("odd", None, None, None)]
    typed = spark.createDataFrame([(1, 0, "user", part)], f"conv_id long, turn long, role string, parts array<{chat.PART}>")
    r = chat.format_chats(typed).first()
    assert r["formatted"] == "<|im_start|>user\nsee <\\|image:2|><|image:2|><|audio:3|><|odd:4|><|im_end|>\n"
    assert [(a["kind"], a["ref"], a["tokens"]) for a in r["attachments"]] == [("image", "a.png", 512), ("audio", "b.wav", 75), ("odd", "", 0)]
    assert r["expanded_tokens"] == 587
    assert chat.format_chats(rows.limit(0)).count() == 0


def plain_rule(url):
    host, path = "", ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:cut])
        rest = rest[cut:]
        path = rest[: min([rest.find(c) for c in "?#" if c in rest], default=len(rest))]
    fit = [r for r in urls.RULES if (host == r[1] or host.endswith("." + r[1])) and path.startswith(r[2])]
    best = max(fit, key=lambda r: len(r[1] + r[2]), default=None)
    return host, path, best and best[1] + best[2], best and best[0]


def test_url_rules_and_method(spark):
    cases = [None, "", "no scheme", "http://A.Example.com/en/1", "https://www.example.com/en/?q=://x/", "http://example.com", "ftp://x.net/es/a#b", "http://x.net?/fr/", "http://net/fr/", "http://spam-farm.example.org/en/9", "http://theand.example.org/de/7", "http://b.com/\n/x", "http://" + "k" * 5000 + ".org/p"]
    rows = spark.createDataFrame([(i, u, "x") for i, u in enumerate(cases)], "page_id long, url string, host string")
    got = {r["page_id"]: r for r in urls.judge(rows.select("page_id", "url"), "page_id").collect()}
    for i, u in enumerate(cases):
        host, path, rule, verdict = plain_rule(u)
        assert (got[i]["host"], got[i]["path"], got[i]["rule"]) == (host, path, rule)
        assert verdict is None or got[i]["verdict"] == verdict
    assert got[9]["verdict"] == "block" and got[10]["verdict"] == "allow"


def test_decontamination_finds_planted_and_leaves_clean(spark, docs):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    items = [" ".join(word() for _ in range(n)) for n in (3, 12, 30, 55, 55)]
    noise = lambda n: " ".join(word() for _ in range(n))
    changed = items[3].split()
    changed[20] = "other"
    texts = [noise(50) + " " + items[1].upper() + " " + noise(9), noise(400), items[2], noise(5) + " " + " ".join(changed), items[0], None, "", " ".join(items[4].split()[:20]) + noise(30)]
    index = [decontaminate.ItemIndex(part) for part in ([(i, t) for i, t in enumerate(items)], [(5, ""), (6, items[1])])]
    got = sorted((r["doc_id"], r["item_id"]) for r in decontaminate.find(docs(texts), index).collect())
    assert got == [(0, 1), (0, 6), (2, 2), (3, 3), (4, 0)]
    left = decontaminate.clean(docs(texts), index)
    assert sorted(r["doc_id"] for r in left.collect()) == [1, 5, 6, 7] and left.columns == ["doc_id", "text", "score"]
    assert decontaminate.find(docs([]), index).count() == 0
    none = docs(texts).selectExpr("doc_id item_id", "text").limit(0)
    assert decontaminate.build(none) == [] and decontaminate.find(docs(texts), []).count() == 0


def plain_components(texts, n, percent):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set())
    own = list(range(len(texts)))
    changed = True
    while changed:
        changed = False
        for i in range(len(texts)):
            for j in range(i):
                both = len(sets[i] & sets[j])
                if sets[i] and sets[j] and 100 * both >= percent * len(sets[i] | sets[j]) and own[i] != own[j]:
                    own = [min(own[i], own[j]) if x in (own[i], own[j]) else x for x in own]
                    changed = True
    return own, [len(s) for s in sets]


@pytest.mark.parametrize("n,percent", [(3, 90), (5, 80)])
def test_jaccard_components_equal_brute_force(spark, docs, n, percent, monkeypatch):
    monkeypatch.setattr(jaccard, "LONG_LIST", 3)  # so that frequent members and long groups come up
    rng = random.Random(n)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(3))
    texts = [None, "", "one", "one", "one two", "ONE\ttwo", " "]
    shared = " ".join(word() for _ in range(60))
    for _ in range(6):
        base = [word() for _ in range(rng.randint(20, 120))]
        for _ in range(rng.randint(1, 9)):
            copy = list(base)
            for _ in range(rng.randint(0, 3)):
                copy[rng.randrange(len(copy))] = word()
            texts.append(" ".join(copy))
    texts += [shared + " " + " ".join(word() for _ in range(40)) for _ in range(6)]
    own, sizes = plain_components(texts, n, percent)
    got = {r["doc_id"]: r for r in jaccard.join(docs(texts), n, percent).collect()}
    assert [got[i]["component_id"] for i in range(len(texts))] == own
    assert [got[i]["n_shingles"] for i in range(len(texts))] == sizes
    assert jaccard.join(docs([]), n, percent).count() == 0


def test_filters_learn_and_keep_rows(spark, docs):
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("etaoinsh") for _ in range(rng.randint(2, 8)))
    good = [" ".join(word() for _ in range(60)) + "." for _ in range(120)]
    junk = [" ".join(word() + "$$$" for _ in range(60)) for _ in range(30)]
    toxic = [" ".join(w if i % 20 else "despicable" for i, w in enumerate(t.split())) for t in good[:40]]
    model = quality.QualityModel(*[np.array([quality.features(t) for t in x]) for x in (good[:100], good[60:] + junk)])
    assert 0.3 < model.prior < 0.97
    s = model.scores([*good[:20], *junk[:20], ""])
    assert s[:20].min() > 0.3 > s[20:40].max() and 0 <= s[40] <= 1
    bad = toxicity.ToxicModel(toxic, good[40:])
    s = bad.scores([*toxic[:20], *good[100:], ""])
    assert s[:20].min() > 0.5 > s[20:].max()
    assert toxicity.ToxicModel([], good).scores(["x", ""]).tolist() == [0, 0]
    rows = docs([*good[:3], *junk[:3], None, ""])
    kept = quality.kept(rows, model)
    assert {0, 1, 2} <= {r["doc_id"] for r in kept.collect()} and kept.columns == rows.columns
    assert {3, 4, 5}.isdisjoint({r["doc_id"] for r in kept.collect()})
    assert toxicity.score_table(docs([]), bad).count() == 0
    assert toxicity.score_table(rows, bad).count() == 8
