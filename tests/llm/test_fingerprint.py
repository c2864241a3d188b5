import hashlib
import math

from lattice_pages.llm import fingerprint


def edited(texts):
    out = []
    for i, t in enumerate(texts):
        n = len(t) // 2
        out.append(t[: len(t) - n] + texts[(i + 1) % len(texts)][:n])
    return out


def jaccard(a, b):
    import re
    from collections import Counter

    w = lambda t: {k: 1 + math.log(v) for k, v in Counter(x for x in re.split(r"[\s!-/:-@\[-`{-~]+", t.lower()) if x).items()}
    a, b = w(a), w(b)
    keys = {*a, *b}
    return sum(min(a.get(k, 0), b.get(k, 0)) for k in keys) / max(1e-9, sum(max(a.get(k, 0), b.get(k, 0)) for k in keys)) if keys else 1.0


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = sorted((r.doc_id, r.text or "") for r in docs.collect())
    texts = [t for _, t in rows]
    got = sorted(fingerprint.fingerprints(docs).collect(), key=lambda r: r.doc_id)
    assert [r.doc_id for r in got] == [i for i, _ in rows]
    off = off_next = 0.0
    by_text = {}
    for r, t, e, nxt in zip(got, texts, edited(texts), texts[1:] + texts[:1]):
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(e.encode()).hexdigest()
        assert by_text.setdefault(t, r.fingerprint) == r.fingerprint and by_text.setdefault(e, r.edited_fingerprint) == r.edited_fingerprint
        off += r.near_edited - jaccard(t, e)
        off_next += r.near_next - jaccard(t, nxt)
    assert abs(off) / len(got) < 0.02 and abs(off_next) / len(got) < 0.02


def test_odd_rows(spark):
    rows = [(5, "a b c d", 1), (5, "a b c d", 1), (None, None, 2), (7, "", 3), (9, "x " * 40000 + "é😀", 4), (5, "other text", 5), (11, "?!", 6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, h int")
    got = fingerprint.fingerprints(docs).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in got) == sorted((i is None, i or 0) for i, _, _ in rows)
    flat = {r.doc_id: r for r in got}
    assert flat[7].fingerprint == flat[11].fingerprint == "0" * 6 * fingerprint.SAMPLES and flat[9].n_chars == 80002
    assert fingerprint.fingerprints(docs.limit(0)).count() == 0
    one = fingerprint.fingerprints(docs.filter("doc_id = 9")).first()
    assert one.near_next == 1.0
