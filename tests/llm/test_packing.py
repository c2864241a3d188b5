import os
import subprocess
import sys
import zlib

import numpy as np
import pytest
from tokenizers import Tokenizer

from lattice_pages.llm import packing
from lattice_pages.llm.byteids import ByteIds
from lattice_pages.llm.queries import vocabulary

VOCAB = vocabulary("byte_bpe_50k.json")
HARD = ["", " ", "  ", "a  b", " a", "a ", "a \nb", "a\n b\n\n c", "it's we'll 'S", "x<|endoftext|>y <|endoftext|>", "é 日本 😀😀", "12 345", "\t\tx\x85 y", "tail   ", "w" * 5000, "<|endof text|>"]


def test_ids_equal_the_library(sf):
    import pyarrow.parquet as pq

    lib, own = Tokenizer.from_file(VOCAB), ByteIds(VOCAB)
    texts = HARD + pq.read_table(f"{sf}/documents.parquet").column("text").to_pylist()
    for t in texts:
        assert np.frombuffer(own.ids(t), "<u4").tolist() == lib.encode(t, add_special_tokens=False).ids


def test_knapsack_is_exact():
    r = np.random.default_rng(1)
    for _ in range(20):
        sizes = np.array(sorted(set(r.integers(1, 12, 4).tolist())))
        worth = r.random(len(sizes))
        best, last = packing.knapsack(sizes, worth, 20)
        slow = [0.0] * 21
        for w in range(1, 21):
            slow[w] = max([slow[w - 1]] + [slow[w - s] + v for s, v in zip(sizes.tolist(), worth.tolist()) if s <= w])
        assert np.allclose(best, slow)
        got = packing._taken(last, sizes, 20, len(sizes))
        assert np.isclose(got @ worth, best[20]) and got @ sizes <= 20


def test_linear_program_reaches_its_bound():
    r = np.random.default_rng(2)
    sizes = np.array(sorted(set(packing.class_of(r.integers(1, 2048, 300)).tolist())))
    demand = r.integers(1, 3000, len(sizes)).astype(float)
    basis, x, bound = packing.column_generation(sizes, demand, 2048)
    assert np.allclose(basis @ x, demand) and (sizes @ basis <= 2048).all()
    assert x[basis.min(axis=0) >= 0].sum() <= bound * 1.005  # the others are surplus, not sequences


def test_inverse():
    a = np.random.default_rng(4).normal(size=(40, 40)) * (np.random.default_rng(5).random((40, 40)) < 0.3) + np.eye(40)[::-1]
    assert np.allclose(packing._inverse(a) @ a, np.eye(40))


LATE_PLAN = """
import numpy as np
from pyspark.sql import SparkSession
from lattice_pages.llm import packing
np.linalg.inv(np.random.default_rng(6).normal(size=(600, 600)))
s = SparkSession.builder.master("local[1]").config("spark.ui.enabled", "false").getOrCreate()
counts = {int(c): 40 for c in packing.class_of(np.arange(3, 2040, 5))}
p = packing.plan(counts)
assert p.sequences * 2048 < sum(c * n for c, n in counts.items()) * 1.03
s.stop()
"""


def test_plan_after_a_session_was_started():
    """Threaded linear algebra before the JVM was started once stopped the plan for ever."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    subprocess.run([sys.executable, "-c", LATE_PLAN], check=True, timeout=150, cwd=root, env=os.environ | {"PYTHONPATH": root})


def test_plan_deals_each_rank_once():
    counts = {2048: 5, 1024: 3, 700: 10, 3: 50, 1: 7}
    p = packing.plan(counts)
    for size, n in counts.items():
        own = np.flatnonzero(p.klass == size)
        assert [*p.lo[own]] == [0, *p.hi[own][:-1]] and p.hi[own][-1] == n


@pytest.mark.parametrize("keep", [False, True])
def test_pack(spark, sf, keep):
    rows = [(i, t, "x", 7) for i, t in enumerate(HARD)] + [(3, HARD[3], "x", 7), (None, None, None, None), (900, "ab " * 20000, "", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, sequence_id string, length int")
    lib = Tokenizer.from_file(VOCAB)
    got = packing.pack(docs, VOCAB, keep_ids=keep).toPandas()
    want = sum(len(lib.encode(t or "", add_special_tokens=False).ids) + 1 for _, t, _, _ in rows)
    assert got.length.sum() == want and (got.length <= 2048).all()
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == [0, *np.cumsum(g.length)[:-1]] and g.length.sum() <= 2048
    if keep:
        seq = packing.sequences(packing.pack(docs, VOCAB, keep_ids=True)).toPandas()
        assert all(len(s) == 4 * (u if u & (u - 1) == 0 else 2048) for s, u in zip(seq.ids, seq.used)) and seq.used.sum() == want
    assert packing.pack(docs.limit(0), VOCAB).count() == 0


def test_little_padding(spark, sf):
    got = packing.pack(spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet"), VOCAB)
    n, tokens = got.agg({"sequence_id": "max", "length": "sum"}).first()
    n, tokens = (n, tokens) if n < tokens else (tokens, n)
    assert (n + 1) * 2048 < tokens * 1.02


def test_query_ids_equal_the_library(spark, sf):
    """The registered query, piece by piece: ids, checksums, places."""
    from lattice_pages.llm.queries import QUERIES

    lib = Tokenizer.from_file(VOCAB)
    want = {}
    for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect():
        ids = np.array(lib.encode(r.text or "", add_special_tokens=False).ids + [1], "<u4")
        want[r.doc_id] = ids
    got = QUERIES["op2_packing"](spark, sf).toPandas()
    for doc, g in got.sort_values("start").groupby("doc_id"):
        ids, at = want.pop(doc), 0
        for r in g.itertuples():
            part = ids[at : at + r.length]
            assert r.start == at and r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(part.tobytes())
            at += r.length
        assert at == len(ids)
    assert not want
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == [0, *np.cumsum(g.length)[:-1]] and g.length.sum() <= 2048


def test_crowded_bucket(spark, monkeypatch):
    monkeypatch.setattr(packing, "BUCKET_ROWS", 5)
    rows = [(7, "same text")] * 400 + [(i, "x " * i) for i in range(60)]
    got = packing.pack(spark.createDataFrame(rows, "doc_id long, text string"), VOCAB).toPandas()
    assert len(got) == 460 and not got.duplicated(["sequence_id", "offset"]).any()
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == [0, *np.cumsum(g.length)[:-1]] and g.length.sum() <= 2048
