"""The pipeline's stages in a chain, each against a plain version on what the stage before kept."""

import random

import pytest
from test_text_operators import plain_components

corpus_pipeline = pytest.importorskip("corpus_pipeline")
from graphdelta.llm import decontaminate, quality, toxicity  # noqa: E402


@pytest.fixture
def tables(spark, tmp_path):
    """Good, junk and toxic texts, near copies, benchmark passages, nulls, repeats, and columns with clashing names."""
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 9)))
    prose = lambda n: " ".join(word() for _ in range(n)) + "."
    items = [prose(30) for _ in range(3)]
    texts = [prose(60) for _ in range(120)] + [" ".join(word() + "$$$" for _ in range(60)) for _ in range(30)]
    texts += [" ".join(w if i % 12 else "despicable" for i, w in enumerate(prose(60).split())) for _ in range(40)]
    quality_of, toxic_of = [1] * 120 + [0] * 30 + [1] * 40, [0] * 150 + [1] * 40
    changed = texts[5].split()
    changed[3] = "other"
    texts += [" ".join(changed), texts[7], prose(20) + " " + items[1] + " " + prose(9), None, "", "one two"]
    rows = [(i, t, "en", "web", 1.5, i) for i, t in enumerate(texts)] + [(None, prose(50), "en", "web", 0.5, 1)]
    write = lambda rows, schema, name: spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / f"{name}.parquet"))
    write(rows, "doc_id long, text string, lang string, source string, score double, n_shingles int", "documents")
    write([(i, q, t) for i, (q, t) in enumerate(zip(quality_of, toxic_of, strict=True))], "doc_id long, quality int, toxic int", "labels")
    write(list(enumerate(items)), "item_id long, text string", "benchmark")
    return str(tmp_path), items


def test_stages_in_a_chain(spark, tables):
    folder, items = tables
    docs = corpus_pipeline.table(spark, folder, "documents")
    labels = corpus_pipeline.table(spark, folder, "labels")
    for name, stage in corpus_pipeline.STAGES:
        before = [(r["doc_id"], r["text"]) for r in docs.collect()]
        if name == "quality":
            scores = quality.train(docs, labels).scores([t or "" for _, t in before])
            want = [i for (i, _), s in zip(before, scores, strict=True) if s >= quality.DECIDE_AT]
        elif name == "toxicity":
            scores = toxicity.train(docs, labels).scores([t or "" for _, t in before])
            want = [i for (i, _), s in zip(before, scores, strict=True) if s < toxicity.DECIDE_AT]
        elif name == "near_copies":
            known = sorted((i, t) for i, t in before if i is not None)
            own, sizes = plain_components([t for _, t in known], 5, 80)
            want = [i for at, (i, _) in enumerate(known) if own[at] == at or not sizes[at]] + [i for i, _ in before if i is None]
        elif name == "benchmark":
            index = decontaminate.ItemIndex(list(enumerate(items)))
            plain = lambda t: any(index.similar(w[a : a + 30], i) >= 0.8 for w in [decontaminate.words_of(t)] for a in range(max(1, len(w) - 29)) for i in range(len(items)))  # noqa: B023, E731
            want = [i for i, t in before if not plain(t)]
        else:
            want = [i for i, _ in before]
        after = stage(spark, docs, folder)
        assert name == "bpe" or after.columns == docs.columns
        kept = corpus_pipeline.saved(after, name)
        order = lambda ids: sorted(ids, key=lambda i: (i is None, i))
        assert order(r["doc_id"] for r in kept.collect()) == order(want), name
        if name == "near_copies":
            ids = {r["doc_id"] for r in kept.collect()}
            assert not {5, 190} <= ids and not {7, 191} <= ids
        if name == "benchmark":
            assert 192 not in {r["doc_id"] for r in kept.collect()}
        docs = kept
    assert sorted(docs.columns) == ["decoded_sha256", "doc_id", "ids_sha256", "n_tokens"]


def test_empty_documents_pass_through(spark, tables, tmp_path_factory):
    folder, _ = tables
    empty = str(tmp_path_factory.mktemp("empty"))
    for name in ("documents", "labels", "benchmark"):
        corpus_pipeline.table(spark, folder, name).limit(0).write.parquet(f"{empty}/{name}.parquet")
    assert corpus_pipeline.run(spark, empty).count() == 0
