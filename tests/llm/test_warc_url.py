import base64
import gzip
import hashlib
import io

from lattice_pages.llm import urlfilter, warc
from lattice_pages.llm.queries import QUERIES


def test_warc_roundtrip(spark):
    rows = [(1, "http://a/x y", "same", 0), (7, "http://b", "same", 0), (3, None, None, 0), (4, "u", "", 0), (5, "u", "\r\n\r\nWARC/1.1\r\n\r\né😀", 0), (6, "", "z" * 3_000_000, 0), (7, "http://b", "same", 0), (None, "n", "null id", 0)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, payload int")
    want = set()
    for i, _, h, _ in rows:
        raw = (h or "").encode()
        top = max((j for j, _, g, _ in rows if (g or "") == (h or "") and j is not None), default=None)
        want.add((i, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "response" if i == top else "revisit", None if i == top else top))
    got = [tuple(r)[:5] for r in warc.archive_roundtrip(df).collect()]
    assert set(got) == want and len(got) == len(rows)
    full = {r.page_id: bytes(r.payload) for r in warc.archive_roundtrip(df, keep_payload=True).collect()}
    assert full[5] == rows[4][2].encode() and full[6] == b"z" * 3_000_000 and full[1] == b""
    assert warc.archive_roundtrip(df.limit(0)).count() == 0


def test_normaliser_makes_members():
    records = [warc.record(i, f"http://h/{i}", b"x" * i, warc.base32_sha1(b"x" * i), None) for i in range(50)]
    out = io.BytesIO()
    index = warc.normalise(io.BytesIO(gzip.compress(b"".join(records))), out)
    for (_, at, n), r in zip(index, records):
        assert gzip.decompress(out.getvalue()[at : at + n]) == r
    assert gzip.decompress(out.getvalue()) == b"".join(records)


def test_rules_and_aliases(spark):
    link = '<html><LINK href="{}" rel="canonical">'
    rows = [
        (1, "http://A.b.Example.com/en/7?x", None),
        (2, "https://x.com/en/5#f", ""),
        (3, "http://other.info/page", link.format("https://x.com/en/5")),
        (4, "http://other.info/dir/more", link.format("/page")),
        (5, "http://free.info/", link.format("//q.net/de/1")),
        (6, "http://free.info/2", '<meta http-equiv="refresh" content="0; url=http://free.info/">'),
        (7, "http://free.info/3", link.format("http://org/es/1")),
        (8, "http://free.info/", link.format("http://free.info/3")),
        (9, None, "x"), (10, "nothing", None), (11, "http://example.net/de/8", None), (12, "http://notexample.net/de/8", None), (13, "://?q", None), (2, "https://x.com/en/5#f", ""),
    ]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("rule", urlfilter.F.lit("clash"))
    got = {(r.page_id, r.host, r.path, r.rule, r.verdict) for r in urlfilter.judge(df).collect()}
    assert got == {
        (1, "a.b.example.com", "/en/7", "example.com/en/7", "allow"), (2, "x.com", "/en/5", "com/en/", "block"), (3, "other.info", "/page", None, "block"), (4, "other.info", "/dir/more", None, "block"),
        (5, "free.info", "/", None, "allow"), (6, "free.info", "/2", None, "allow"), (7, "free.info", "/3", None, "allow"), (8, "free.info", "/", None, "allow"),
        (9, "", "", None, "allow"), (10, "", "", None, "allow"), (11, "example.net", "/de/8", "example.net/de/8", "block"), (12, "notexample.net", "/de/8", "net/de/", "allow"), (13, "", "", None, "allow"),
    }
    moved = spark.createDataFrame([("http://moved.info/a", "http://x.com/en/1")], "source string, target string")
    one = spark.createDataFrame([(1, "http://moved.info/a", None)], "page_id long, url string, html string")
    assert urlfilter.judge(one, redirects=moved).first().verdict == "block"
    assert urlfilter.judge(df.limit(0)).count() == 0


def test_resolve(spark):
    base = "http://H.org/a/b/page.html?x=1#f"
    want = {
        "mailto:me@h.org": None, "javascript:void(0)": None, "?q=2": "http://h.org/a/b/page.html?q=2", "#top": base, "": base,
        "./c": "http://h.org/a/b/c", "../c": "http://h.org/a/c", "../../../c?x=../y": "http://h.org/c?x=../y", "/d/./e/../f": "http://h.org/d/f", "..": "http://h.org/a/", ".": "http://h.org/a/b/", "c?a=1&amp;b=2": "http://h.org/a/b/c?a=1&b=2",
        "//k.net/x": "http://k.net/x", "https://k.net/../x": "https://k.net/../x", "/": "http://h.org/", "c/": "http://h.org/a/b/c/", " c ": "http://h.org/a/b/c",
    }
    df = spark.createDataFrame([(base, k) for k in want], "u string, l string")
    got = {r.l: r.r for r in df.select("l", urlfilter.resolve(urlfilter.F.col("u"), urlfilter.F.col("l")).alias("r")).collect()}
    assert got == want
    bare = spark.createDataFrame([("http://h.org", "?q")], "u string, l string")
    assert bare.select(urlfilter.resolve(urlfilter.F.col("u"), urlfilter.F.col("l"))).first()[0] == "http://h.org/?q"


def test_warc_query_equals_brute_force(spark, sf):
    rows = spark.read.parquet(f"{sf}/pages.parquet").collect()
    groups = {}
    for r in rows:
        groups.setdefault(r.html or "", []).append(r.page_id)
    want = {(r.page_id, len((r.html or "").encode()), base64.b32encode(hashlib.sha1((r.html or "").encode()).digest()).decode(), "response" if r.page_id == max(groups[r.html or ""]) else "revisit", None if r.page_id == max(groups[r.html or ""]) else max(groups[r.html or ""])) for r in rows}
    assert {tuple(r)[:5] for r in QUERIES["op1_warc"](spark, sf).collect()} == want


def test_queries_run(spark, sf):
    import duckdb

    n = spark.read.parquet(f"{sf}/pages.parquet").count()
    assert QUERIES["op1_warc"](spark, sf).count() == n
    got = sorted(tuple(r) for r in QUERIES["op8_url_filter"](spark, sf).collect())
    duckdb.sql(f"create or replace view pages as select * from '{sf}/pages.parquet'")
    assert sorted(duckdb.sql(urlfilter.ORACLE).fetchall()) == got
