"""What a task of the pipeline holds at once stays bounded, with the same results."""

import random
import tracemalloc

import numpy as np
import pyarrow as pa
import pytest

from lattice_pages import session
from lattice_pages.llm import langid


@pytest.mark.parametrize("name", ["language", "near_copies", "personal_data", "packing"])
def test_stages_run_on_batches_of_bounded_bytes(spark, sf, name):
    pipeline = pytest.importorskip("corpus_pipeline")
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    was = spark.conf.get(key)

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(b)]), pa.array([b.nbytes])], ["n", "bytes"])

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").limit(5)
    large = spark.range(3000, numPartitions=1).selectExpr("repeat(char(97 + id % 26), 4000) AS text")
    try:
        dict(pipeline.STAGES)[name](spark, docs, sf)
        got = large.mapInArrow(sizes, "n long, bytes long").collect()
        assert sum(r.n for r in got) == 3000 and max(r.bytes for r in got) <= 1.1 * session.BATCH_BYTES
        spark.conf.set(key, "100k")  # a lower bound stays
        dict(pipeline.STAGES)["language"](spark, docs, sf)
        assert spark.conf.get(key) == "100k"
    finally:
        spark.conf.set(key, was)


def test_new_chunks_are_hashed_in_bounded_passes(monkeypatch):
    r = random.Random(3)
    chunks = sorted({"".join(r.choices("abcdefghijé", k=r.randint(1, 12))) for _ in range(60_000)} | {"", "12", "x" * 200_000})
    m = langid.Model(["a", "b", "c"], np.random.default_rng(1).normal(size=(langid.BUCKETS, 3)).astype(np.float32), np.zeros(3), 1.0, 0.0)

    def learned():
        s = langid.Scorer(m)
        tracemalloc.start()
        s.learn(chunks)
        most = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        return s.rows[[s.at[c] for c in chunks]], most

    rows, most = learned()
    monkeypatch.setattr(langid.Scorer, "PASS", 1 << 40)
    whole, more = learned()
    assert (rows == whole).all() and most < 0.7 * more


def test_a_worker_gives_memory_back_when_its_task_ends(monkeypatch):
    done = []
    monkeypatch.setattr(session, "give_back", lambda: done.append(1))
    task = session.sparing(lambda batches: (b for b in batches))
    assert list(task(iter([1, 2]))) == [1, 2] and done == [1]
    early = task(iter([1, 2]))
    assert next(early) == 1
    early.close()
    assert done == [1, 1]
