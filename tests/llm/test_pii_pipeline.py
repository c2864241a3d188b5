import hashlib
import re
import zlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from lattice_pages.llm import langid, pii

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")


def plain(text):
    got = [("email", *m.span()) for m in EMAIL.finditer(text)]
    got += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub("[^0-9]", "", m.group())
        if 16 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(d[::-1])) % 10 == 0:
            got.append(("card", *m.span()))
    got += [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return got


@settings(max_examples=300)
@given(st.lists(st.sampled_from(["a", "@", ".", "b.c", "@d.e", " ", "+1", "(415)", "555", "-", "4111111111111111", "1.2.3.4", "256.1.1.1", "é", "@@", "x@y.z@w.v", "0001"]), max_size=14).map("".join))
def test_base_equals_plain_patterns(text):
    assert pii.base_spans(text) == plain(text)


def test_long_runs_of_zeros():
    assert pii.base_spans("0" * 5000 + ".1.1.1") == [("ip", 0, 5006)] and not [s for s in pii.base_spans("1" * 5000 + ".1.1.1") if s[0] == "ip"]


def digest(spans):
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def test_registered_query(spark, sf):
    """op5_pii over the whole table against the plain patterns; added spans come from the model."""
    from lattice_pages.llm.queries import QUERIES

    texts = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    m = pii.model()
    got = QUERIES["op5_pii"](spark, sf).collect()
    assert sorted(r.doc_id for r in got) == sorted(texts)
    for r in got:
        base = plain(texts[r.doc_id])
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == x for k, _, _ in base) for x in pii.KINDS]
        assert r.base_sha256 == hashlib.sha256(digest(base).encode()).hexdigest()
        spans = pii.all_spans([texts[r.doc_id]], m)[0][1]
        assert r.spans == digest(spans) and set(base) <= set(spans)


def test_model_adds_what_the_base_misses():
    m = pii.model()
    text = "erntou +1 (269) 555-3296 4524132264652876 and on. mail joe (at) host.com now, version 1.2.3.4.5 and 12345678 by 978-3-16-148410-0"
    base, spans = pii.all_spans([text], m)[0]
    found = {(k, text[a:b]) for k, a, b in spans}
    assert ("phone", "+1 (269) 555-3296") in found and set(base) <= set(spans)
    clean = ["The 3.0. licence, 2.0.1 and 4.0.", "password=b7db7aa4a5fcc78305 token = \"1beb58b8af68854f0e01b4ad40cdbb6ae7f578ae\"", "in 2024-01-02 10:11 there were 1,234,567 of 12 345 678"]
    assert all(not s for _, s in pii.all_spans(clean, m))


def test_detect_and_redact(spark):
    rows = [(1, "write a.b@c.org or 10.0.0.1", "e", "s", 27), (2, None, None, None, None), (3, "", "e", "s", 0), (1, "x " * 100000 + "+1 (415) 555-2671", "e", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, spans string, source string, n_chars long")
    got = sorted(((r.doc_id, r.n_email, r.n_ip, r.n_card, r.n_phone) for r in pii.detect(docs).collect()))
    assert got == [(1, 0, 0, 0, 1), (1, 1, 1, 0, 0), (2, 0, 0, 0, 0), (3, 0, 0, 0, 0)]
    kept = pii.redact(docs, length_col="n_chars")
    assert kept.schema == docs.schema
    assert {(r.doc_id, r.text if (r.n_chars or 0) < 99 else r.text[-8:]) for r in kept.collect()} == {(1, "write [EMAIL] or [IP]"), (2, None), (3, ""), (1, " [PHONE]")}
    assert pii.detect(docs.limit(0)).count() == 0


def test_language(spark, sf):
    docs = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    got = langid.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r.held_out and r.lang and r.lang_pred != "und"]
    assert len(held) > 100 and sum(r.lang == r.lang_pred for r in held) / len(held) > 0.95
    assert all(0 <= r.score <= 1 for r in got) and sum(not r.accepted for r in got) < 0.02 * len(got)
    odd = spark.createDataFrame([(1, None, "en", 0.5), (2, "", "en", 0.5), (3, "12 !?", "en", 0.5), (3, "12 !?", "en", 0.5)], "doc_id long, text string, lang string, score double")
    assert [r.lang_pred for r in langid.identify(odd).collect()] == ["und"] * 4
    assert langid.identify(docs.limit(0)).count() == 0


def test_only_letters_count():
    assert not langid._LETTERS.search("\u00bd \u00b2 \u2167 12 _ !")  # a half, a superscript, a Roman-numeral sign
    assert langid._LETTERS.findall("\u00e9x2\u00b2 \u65e5\u672c") == ["\u00e9x", "\u65e5\u672c"]


def test_registered_language_query(spark, sf):
    from lattice_pages.llm.queries import QUERIES

    docs = {r.doc_id: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    learned = {r.lang for i, r in docs.items() if zlib.crc32(str(i).encode()) % 5 and r.lang is not None}
    got = QUERIES["op6_language"](spark, sf).collect()
    assert sorted(r.doc_id for r in got) == sorted(docs)
    for r in got:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1
        assert (r.lang_pred == "und") == (not any(c.isalpha() for c in docs[r.doc_id].text or "")) and r.lang_pred in learned | {"und"}


def test_labels_of_the_held_out_fold_are_not_read(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    fold = F.crc32(F.col("doc_id").cast("string")) % 5 == 0
    other = docs.withColumn("lang", F.when(fold, "zz").otherwise(F.col("lang"))).withColumn("source", F.lit(None))
    key = lambda d: sorted((r.doc_id, r.lang_pred, r.score) for r in langid.identify(d).collect())
    assert key(docs) == key(other)


def shingle_set(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]+", lambda m: m.group().lower(), text or ""))
    return {" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


ODD = [(1, None, None, None, None, 7), (2, "", "en", "s", 0, 7), (None, "x", "en", "s", 1, 7), (4, "12 !", "en", "s", 4, 7)]


def test_pipeline_stages_on_odd_tables(spark, sf):
    """Null, empty, repeated and clashing input, and an empty table, go through every stage."""
    pipeline = pytest.importorskip("corpus_pipeline")
    real = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").limit(60).collect()
    kind = "doc_id long, text string, lang string, source string, n_chars long, component long"
    odd = ODD + [(r.doc_id + 100, r.text, r.lang, r.source, r.n_chars, 7) for r in real] + [(r.doc_id + 100, r.text, r.lang, r.source, r.n_chars, 7) for r in real[:5]]
    for rows in (odd, ODD, []):
        docs = spark.createDataFrame(rows, kind)
        for name, stage in pipeline.STAGES:
            docs, was = stage(spark, docs, sf), docs
            if name != "packing":
                assert docs.columns == was.columns
            docs = docs.cache()
            assert docs.count() > 0 if rows is odd else docs.count() >= 0


def test_pipeline_against_brute_force(spark, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = docs
    for name, stage in pipeline.STAGES[:-1]:
        nxt = stage(spark, out, sf)
        assert nxt.columns == docs.columns
        rows = {r.doc_id: r for r in out.collect()}
        if name == "near_copies":
            sets = {i: shingle_set(r.text) for i, r in rows.items()}
            label = {i: i for i in sets}
            links = [(i, j) for i in sets for j in sets if i < j and (5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]))]
            for _ in range(len(sets)):
                was = dict(label)
                for i, j in links:
                    label[i] = label[j] = min(label[i], label[j])
                if was == label:
                    break
            assert {r.doc_id for r in nxt.collect()} == set(label.values())
        if name == "personal_data":
            m = pii.model()
            for r in nxt.collect():
                assert r.text == pii.replace(rows[r.doc_id].text, pii.all_spans([rows[r.doc_id].text], m)[0][1])
        out = nxt
    final = pipeline.run(spark, sf)
    assert {r.doc_id for r in final.select("doc_id").collect()} == {r.doc_id for r in out.collect()}
