"""Document fingerprints by consistent weighted sampling, DataFrame functions only.

Terms are lower-case words with weight 1 + ln(count). For sample k a term draws, from
hashes of (term, k), r and c from Gamma(2, 1) and b from the unit interval; with weight
w its level is t = floor(ln w / r + b) and its key ln c - r (t - b + 1). The term and
level of the least key are the document's sample, so two documents share a sample with
the probability of their generalised Jaccard similarity. ``SAMPLES`` samples, 24 bits
each, make the fingerprint.

Layout: texts are dealt out by their key once. The first half of each text travels to
the document before it, at most half of the bytes; everything after that (words,
counts, samples) stays within the partition the text is in, because all its grouping keys
contain the document's. The order of documents is found on ids alone: a range
partitioning, then the rows at the partition edges.

Defined results: a null text counts as empty; texts without words have the fingerprint
of all zeros and likeness 1 to each other, 0 to others; rows that repeat id and text
count as one document and get a row each; rows that share an id are ordered by a hash
of the text; null ids come first; the only document is its own neighbour; an empty table
gives an empty table. Only the id and text columns are read, so other columns cannot clash.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lattice_pages.session import materialize

SAMPLES = 32
_MASK = (1 << 24) - 1


def _unit(bits: Column, width: int) -> Column:
    """A value inside (0, 1) from the low ``width`` bits."""
    return (bits.bitwiseAND(F.lit((1 << width) - 1)) + F.lit(0.5)) * F.lit(2.0**-width)


def sample_key(term: Column, k: int, log_weight: Column) -> Column:
    """A long whose order is that of the sampling key; its low 24 bits name (term, level)."""
    h1 = F.xxhash64(term, F.lit(k))
    h2 = F.xxhash64(h1, F.lit(k))
    r = -F.log(_unit(h1, 21) * _unit(F.shiftrightunsigned(h1, 21), 21))
    b = _unit(F.shiftrightunsigned(h1, 42), 22)
    c = -F.log(_unit(h2, 32) * _unit(F.shiftrightunsigned(h2, 32), 32))
    t = F.floor(log_weight / r + b)
    key = F.log(c) - r * (t - b + F.lit(1.0))
    place = ((key + F.lit(64.0)) * F.lit(float(1 << 32))).cast("long")
    name = (h2 + t * F.lit(0x9E3779B1)).bitwiseAND(F.lit(_MASK))
    return F.shiftleft(F.greatest(place, F.lit(0).cast("long")), 24).bitwiseOR(name)


def neighbours(ids: DataFrame) -> DataFrame:
    """``k, h, n, copies`` with the keys of the documents before and after, and n of the one before.

    ``ids``: ``k, h, n``, possibly repeated. The order is (k, h), closed to a ring.
    """
    one = ids.groupBy("k", "h").agg(F.max("n").alias("n"), F.count(F.lit(1)).alias("copies"))
    one = materialize(one.repartitionByRange("k", "h").withColumn("part", F.spark_partition_id()), "order")
    here = Window.partitionBy("part").orderBy("k", "h")
    row = F.struct("k", "h", "n")
    inner = one.select("*", F.lag(row).over(here).alias("before"), F.lead(row).over(here).alias("after"))
    edges = one.groupBy("part").agg(F.min(row).alias("head"), F.max(row).alias("tail"))  # one row a partition
    parts = Window.orderBy("part")
    ends = edges.agg(F.min_by("head", "part").alias("first"), F.max_by("tail", "part").alias("last"))
    edges = edges.select("part", F.lag("tail").over(parts).alias("tail"), F.lead("head").over(parts).alias("head")).crossJoin(F.broadcast(ends))
    edges = edges.select("part", F.coalesce("tail", "last").alias("tail"), F.coalesce("head", "first").alias("head"))
    got = inner.join(F.broadcast(edges), "part")
    got = got.select("k", "h", "n", "copies", F.coalesce("before", "tail").alias("before"), F.coalesce("after", "head").alias("after"))
    return materialize(got.select("k", "h", "n", "copies", F.col("before.k").alias("pk"), F.col("before.h").alias("ph"), F.col("before.n").alias("pn"), F.col("after.k").alias("nk"), F.col("after.h").alias("nh")), "neighbours")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", samples: int = SAMPLES) -> DataFrame:
    """The columns of the query: see the module's text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    least = F.lit(-(1 << 63)).cast("long")
    texts = docs.select(F.coalesce(F.col(id_col).cast("long"), least).alias("k"), F.xxhash64(text).alias("h"), text.alias("text"))
    order = neighbours(texts.select("k", "h", F.length("text").alias("n")))

    # repeated rows meet here; every later key contains (k, h), so this is the only exchange of whole texts
    dealt = texts.groupBy("k", "h").agg(F.first("text").alias("text"))
    half = F.floor(F.col("pn") / 2).cast("int")
    heads = dealt.join(order, ["k", "h"]).select(F.col("pk").alias("k"), F.col("ph").alias("h"), F.substring("text", F.lit(1), half).alias("head"))
    n = F.length("text")
    both = dealt.join(heads, ["k", "h"]).select("k", "h", "text", F.concat(F.substring("text", F.lit(1), n - F.floor(n / 2).cast("int")), "head").alias("edited"))
    digests = both.select("k", "h", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"))

    words = lambda c: F.split(F.lower(c), r"[\s\p{Punct}]+")
    sides = F.array(F.struct(F.lit(0).alias("side"), words("text").alias("w")), F.struct(F.lit(1).alias("side"), words("edited").alias("w")))
    rows = both.select("k", "h", F.explode(sides).alias("s")).select("k", "h", "s.side", F.explode("s.w").alias("word")).filter("word <> ''")
    terms = rows.groupBy("k", "h", F.xxhash64("word").alias("term")).agg(F.sum(F.when(F.col("side") == 0, 1).otherwise(0)).alias("c0"), F.sum(F.when(F.col("side") == 1, 1).otherwise(0)).alias("c1"))
    w = lambda c: F.log(F.col(c).cast("double"))
    terms = terms.select("k", "h", "term", F.when(F.col("c0") > 0, F.log(w("c0") + 1)).alias("w0"), F.when(F.col("c1") > 0, F.log(w("c1") + 1)).alias("w1"))
    mins = [F.min(sample_key(F.col("term"), i, F.col(f"w{s}"))).alias(f"m{s}_{i}") for s in (0, 1) for i in range(samples)]
    drawn = terms.groupBy("k", "h").agg(*mins)

    def names(s: int) -> Column:
        return F.array(*[F.coalesce(F.greatest(F.col(f"m{s}_{i}").bitwiseAND(F.lit(_MASK)).cast("int"), F.lit(1)), F.lit(0)) for i in range(samples)])

    drawn = digests.join(drawn.select("k", "h", names(0).alias("a"), names(1).alias("e")), ["k", "h"], "left")
    drawn = materialize(drawn, "samples")
    none = F.array_repeat(F.lit(0), samples)
    own = order.join(drawn, ["k", "h"], "left").select(*order.columns, "edited_sha256", F.coalesce("a", none).alias("a"), F.coalesce("e", none).alias("e"))
    after = own.select(F.col("k").alias("nk"), F.col("h").alias("nh"), F.col("a").alias("x"))
    full = own.join(after, ["nk", "nh"])

    def likeness(x: str, y: str) -> Column:
        return sum((F.when(F.col(x)[i] == F.col(y)[i], 1).otherwise(0) for i in range(samples)), F.lit(0)) / F.lit(float(samples))

    def shown(x: str) -> Column:
        return F.concat(*[F.lower(F.lpad(F.hex(F.col(x)[i].cast("long")), 6, "0")) for i in range(samples)])

    kind = docs.schema[id_col].dataType.simpleString()
    full = full.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return full.select(F.when(F.col("k") != least, F.col("k")).cast(kind).alias(id_col), F.col("n").cast("long").alias("n_chars"), "edited_sha256", shown("a").alias("fingerprint"), shown("e").alias("edited_fingerprint"), likeness("a", "e").alias("near_edited"), likeness("a", "x").alias("near_next"))
