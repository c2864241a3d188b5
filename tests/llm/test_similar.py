from fractions import Fraction

import numpy as np
import pytest

from lattice_pages.llm import similar


def plain(text, words=5):
    w = (text or "").encode().lower().split()
    return {b" ".join(w[i : i + words]) for i in range(max(1, len(w) - words + 1))} if w else set()


def brute(texts, least=Fraction(4, 5)):
    """Least row number reachable over pairs of the similarity."""
    sets = [plain(t) for t in texts]
    label = list(range(len(sets)))
    near = [[j for j, b in enumerate(sets) if a == b or (a | b and Fraction(len(a & b), len(a | b)) >= least)] for a in sets]
    while True:
        new = [min(label[j] for j in js) for js in near]
        if new == label:
            return label
        label = new


@pytest.mark.parametrize("size", ["0.001", "0.01"])
def test_pipeline_stage_equals_brute_force(spark, sf, size):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf.replace('0.001', size)}/documents.parquet")
    rows = sorted((r.doc_id, r.text) for r in docs.collect())
    want = {rows[i][0] for i in brute([t for _, t in rows])}
    got = corpus_pipeline.near_copies(spark, docs, sf)
    assert got.columns == docs.columns
    assert sorted(r.doc_id for r in got.collect()) == sorted(want)


def test_chains_and_boundaries(spark):
    r = np.random.default_rng(5)
    texts = []
    for _ in range(12):  # chains of edits, whose ends are not similar, and exact boundaries
        w = [f"w{x}" for x in r.integers(0, 10**6, int(r.integers(6, 120)))]
        for _ in range(8):
            texts.append(" ".join(w))
            for at in r.integers(0, len(w), 1 + len(w) // 60):
                w[int(at)] = f"w{r.integers(0, 10**6)}"
    texts += ["a b c d e f g h i j k l m", "a b c d e f g h i j k l", "x a b c d e f g h i j k l m y", "one", "ONE", "one two"]
    label = brute(texts)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert sorted(x.doc_id for x in similar.keep_one(df).collect()) == sorted(set(label))


def test_repeated_and_null_ids(spark):
    rows = [(3, "a b c d e f"), (3, "u v w x y z"), (3, "u v w x y z"), (4, "A b  c d e f"), (None, "p q r s t u"), (None, "p q r s t u"), (None, "u v w x y z"), (7, None), (8, " ")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.text) for r in similar.keep_one(df).collect()), key=repr)
    assert got == sorted([(3, "a b c d e f"), (3, "u v w x y z"), (None, "p q r s t u"), (7, None)], key=repr)
    assert similar.keep_one(df.limit(0)).count() == 0


def test_repeated_rows_among_near_copies(spark, monkeypatch):
    r = np.random.default_rng(6)
    texts = []
    for _ in range(6):
        w = [f"w{x}" for x in r.integers(0, 10**6, 90)]
        for k in range(4):
            texts.append(" ".join(w[: 90 - k]))
    label = brute(texts)
    rows = [(i, t) for i, t in enumerate(texts) for _ in range(1 + i % 3)] + [(None, texts[0])] * 2
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = sorted(set(label))
    assert sorted(x.doc_id for x in similar.keep_one(df).collect()) == want
    monkeypatch.setattr(similar, "BROADCAST", 0)  # the way of long tables
    assert sorted(x.doc_id for x in similar.keep_one(df).collect()) == want


def test_sketches_never_differ_more_than_the_sets():
    r = np.random.default_rng(9)
    for n in (0, 1, 5, 80, 700, 5000):
        a = np.unique(r.integers(0, 2**63, n).astype(np.uint64))
        b = np.unique(np.concatenate([a[: n * 9 // 10], r.integers(0, 2**63, n // 8).astype(np.uint64)]))
        bits = int(np.bitwise_count((similar.sketch(a) ^ similar.sketch(b)).view(np.uint64)).sum())
        assert bits <= len(np.setxor1d(a, b))


def test_pipeline_stage_goes_through_the_simhash_operator(spark, sf, monkeypatch):
    """With the buckets of the set join emptied, the links that stay are those of the anchor points."""
    import corpus_pipeline
    from lattice_pages.llm import simhash

    seen, was = [], simhash.links
    monkeypatch.setattr(simhash, "links", lambda nodes, *a: seen.append(nodes.count()) or was(nodes, *a))
    monkeypatch.setattr(similar, "prefix", lambda s, *a: s[:0])
    r = np.random.default_rng(11)
    w = [f"w{x}" for x in r.integers(0, 10**6, 900)]
    texts = [" ".join(w), " ".join([*w[:-1], "other"]), " ".join(f"v{x}" for x in r.integers(0, 10**6, 900))]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    assert sorted(x.doc_id for x in corpus_pipeline.near_copies(spark, df, sf).collect()) == [0, 2]
    assert seen and seen[0] >= 2


def test_batches_are_bounded_by_bytes(spark):
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    was = spark.conf.get(key)
    with similar._small_batches(spark):
        df = spark.range(400).repartition(1).selectExpr("repeat('x', 100000) AS t")
        sizes = [x.n for x in df.mapInArrow(lambda bs: (similar.pa.RecordBatch.from_arrays([similar.pa.array([b.nbytes])], ["n"]) for b in bs), "n long").collect()]
    assert max(sizes) <= similar.BATCH_BYTES + 200_000 and len(sizes) > 5
    assert spark.conf.get(key) == was
