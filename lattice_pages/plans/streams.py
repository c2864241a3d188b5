"""The catalogue of ordered streams on the given tables, in Spark SQL and in DuckDB SQL.

Each stream is a table expression with a total order. Where the two engines spell a
function differently, ``duck`` holds the other spelling.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lattice_pages.operators.pages import across, with_ordinal

LINEITEM = ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
#: The labels of the given tables.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
_US = "timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', ts)"
_DUCK_US = "epoch_us(ts)"


@dataclass(frozen=True)
class Stream:
    name: str
    table: str
    value: str
    order: tuple[str, ...]
    duck: str | None = None
    where: str = "true"
    domain: str = ""
    cents: bool = False  # the value is a sum of cents, divided by 100 at the end

    def spark_sql(self) -> str:
        return f"SELECT {', '.join(self.order)}, {self.value} AS value FROM {self.table} WHERE {self.where}"

    def duck_sql(self) -> str:
        """``ord, value`` in DuckDB."""
        v = self.duck or self.value
        return f"SELECT row_number() OVER (ORDER BY {', '.join(self.order)}) - 1 AS ord, {v} AS value FROM {self.table} WHERE {self.where}"


def _s(name: str, table: str, value: str, order: str | tuple, duck: str | None = None, **kw) -> Stream:
    return Stream(name, table, value, (order,) if isinstance(order, str) else order, duck, **kw)


EXACT14 = (
    _s("part_price", "part", "p_retailprice", "p_partkey", domain="masters"),
    _s("li_discount", "lineitem", "l_discount", LINEITEM, domain="lineitem"),
    _s("li_tax", "lineitem", "l_tax", LINEITEM, domain="lineitem"),
    _s("li_quantity", "lineitem", "l_quantity", LINEITEM, domain="lineitem"),
    _s("ev_cum", "events", "CAST(sum(CAST(round(value * 100, 0) AS BIGINT)) OVER (ORDER BY event_id) AS BIGINT) / 100.0D", "event_id", "CAST(sum(CAST(round(value * 100, 0) AS BIGINT)) OVER (ORDER BY event_id) AS BIGINT)::DOUBLE / 100.0::DOUBLE", domain="events"),
    _s("ev_value", "events", "value", "event_id", domain="events"),
    _s("ord_total", "orders", "o_totalprice", ("o_orderdate", "o_orderkey"), domain="orders"),
    _s("ev_minute", "events", f"CAST({_US} div 60000000 * 60 AS DOUBLE)", "event_id", f"({_DUCK_US} // 60000000 * 60)::DOUBLE", domain="events"),
    _s("ev_epoch", "events", f"CAST({_US} AS DOUBLE) / 1000000.0D", "event_id", f"{_DUCK_US}::DOUBLE / 1000000.0::DOUBLE", domain="events"),
    _s("ev_gap", f"(SELECT event_id, {_US} - lag({_US}) OVER (ORDER BY event_id) AS gap FROM events)", "CAST(gap AS DOUBLE) / 1000000.0D", "event_id", "gap::DOUBLE / 1000000.0::DOUBLE", where="gap IS NOT NULL", domain="events"),
    _s("li_unit", "lineitem", "l_extendedprice / l_quantity", LINEITEM, domain="lineitem"),
    _s("li_price", "lineitem", "l_extendedprice", LINEITEM, domain="lineitem"),
    _s("cust_bal", "customer", "c_acctbal", "c_custkey", domain="masters"),
    _s("emb_flat", "(SELECT vec_id, pos, e FROM embeddings LATERAL VIEW posexplode(embedding) t AS pos, e)", "CAST(e AS DOUBLE)", ("vec_id", "pos"), domain="vectors"),
)
ORD_DAILY = _s("ord_daily", "(SELECT o_orderdate, sum(CAST(round(o_totalprice * 100, 0) AS BIGINT)) AS cents FROM orders GROUP BY o_orderdate)", "CAST(cents AS DOUBLE) / 100.0D", "o_orderdate", "cents::DOUBLE / 100.0::DOUBLE", domain="orders")
BOUNDED15 = (*EXACT14, ORD_DAILY)

_DUCK_TABLE = {
    "ev_gap": f"(SELECT event_id, {_DUCK_US} - lag({_DUCK_US}) OVER (ORDER BY event_id) AS gap FROM events)",
    "emb_flat": "(SELECT vec_id, unnest(range(len(embedding))) AS pos, unnest(embedding) AS e FROM embeddings)",
}


def duck_sql(s: Stream) -> str:
    table = _DUCK_TABLE.get(s.name, s.table)
    return s.duck_sql().replace(f"FROM {s.table} WHERE", f"FROM {table} WHERE") if table != s.table else s.duck_sql()


def large48() -> tuple[Stream, ...]:
    """Forty-eight streams in four domains."""
    out = []
    for flag in "ANR":
        for status in "FO":
            for m in ("l_quantity", "l_extendedprice", "l_discount", "l_tax"):
                out.append(_s(f"li_{flag}{status}_{m}", "lineitem", m, LINEITEM, where=f"l_returnflag = '{flag}' AND l_linestatus = '{status}'", domain="lineitem"))
    gap = f"(SELECT event_id, event_type, {_US} - lag({_US}) OVER (PARTITION BY event_type ORDER BY event_id) AS gap FROM events)"
    for kind in EVENT_TYPES:
        here = f"event_type = '{kind}'"
        out.append(_s(f"ev_{kind}_value", "events", "value", "event_id", where=here, domain="events"))
        out.append(_s(f"ev_{kind}_epoch", "events", f"CAST({_US} AS DOUBLE) / 1000000.0D", "event_id", where=here, domain="events"))
        out.append(_s(f"ev_{kind}_gap", gap, "CAST(gap AS DOUBLE) / 1000000.0D", "event_id", where=f"{here} AND gap IS NOT NULL", domain="events"))
    for k in PRIORITIES:
        out.append(_s(f"ord_{k[0]}", "orders", "o_totalprice", ("o_orderdate", "o_orderkey"), where=f"o_orderpriority = '{k}'", domain="orders"))
    for name, table, value, key in (("cust_bal", "customer", "c_acctbal", "c_custkey"), ("supp_bal", "supplier", "s_acctbal", "s_suppkey"), ("part_price", "part", "p_retailprice", "p_partkey"), ("doc_chars", "documents", "CAST(n_chars AS DOUBLE)", "doc_id")):
        out.append(_s(f"master_{name}", table, value, key, domain="masters"))
    return tuple(out)


def all_keyed(spark: SparkSession, sf_dir: str, many: tuple[Stream, ...]) -> tuple[DataFrame, list[str]]:
    """Rows of many streams in one frame, and the order columns that all of them share."""
    register(spark, sf_dir)
    out, width = None, max(len(s.order) for s in many)
    tables: dict[tuple, list[Stream]] = {}
    for s in many:
        tables.setdefault((s.table, s.order), []).append(s)
    for (table, order), own in tables.items():  # one scan of each table
        dated = order[0].endswith("date")
        keys = [*([] if dated else ["CAST(NULL AS TIMESTAMP_NTZ)"]), *order]
        keys += ["0"] * (width - len(keys))
        cols = ", ".join(f"CAST({k} AS {'TIMESTAMP_NTZ' if i == 0 else 'BIGINT'}) AS k{i}" for i, k in enumerate(keys))
        each = ", ".join(f"CASE WHEN {s.where} THEN named_struct('stream_id', '{s.name}', 'domain', '{s.domain}', 'value', {s.value}) END" for s in own)
        rows = spark.sql(f"SELECT {cols}, explode(array_compact(array({each}))) AS x FROM {table}").select("x.stream_id", "x.domain", *[f"k{i}" for i in range(width)], "x.value")
        out = rows if out is None else out.unionByName(rows)
    return out, [f"k{i}" for i in range(width)]


BY_NAME = {s.name: s for s in BOUNDED15}


def catalogue(kind: str) -> list[Stream]:
    return {"exact14": list(EXACT14), "bounded15": list(BOUNDED15), "large48": list(large48())}[kind]


def register(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = ("part", "lineitem", "orders", "events", "customer", "supplier", "embeddings", "documents")) -> None:
    for t in tables:
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)


def keyed(spark: SparkSession, sf_dir: str, s: Stream | str) -> DataFrame:
    """The stream's rows with their order columns, unnumbered."""
    s = BY_NAME[s] if isinstance(s, str) else s
    register(spark, sf_dir)
    if s.name == "ev_cum":  # no window over the whole table
        cents = spark.sql("SELECT event_id, CAST(round(value * 100, 0) AS BIGINT) AS cents FROM events")
        rows = across(cents, ["event_id"], "cents").select("event_id", F.expr("running / 100.0D").alias("value"))
    elif s.name == "ev_gap":
        times = spark.sql(f"SELECT event_id, {_US} AS us FROM events")
        rows = across(times, ["event_id"], "us").filter("previous IS NOT NULL").select("event_id", F.expr("CAST(us - previous AS DOUBLE) / 1000000.0D").alias("value"))
    else:
        rows = spark.sql(s.spark_sql())
    return rows.withColumn("stream_id", F.lit(s.name))


def stream_df(spark: SparkSession, sf_dir: str, s: Stream | str, method: str = "range") -> DataFrame:
    """``stream_id, ord, value``."""
    s = BY_NAME[s] if isinstance(s, str) else s
    return with_ordinal(keyed(spark, sf_dir, s), "stream_id", list(s.order), method).select("stream_id", "ord", "value")


def together(spark: SparkSession, sf_dir: str, many: tuple[Stream, ...]) -> DataFrame:
    """``stream_id, ord, value`` of many streams; those of one table in one order are numbered once."""
    register(spark, sf_dir)
    out, tables = None, {}
    for s in many:
        tables.setdefault(s.name if s.name in ("ev_cum", "ev_gap") else (s.table, s.order, s.where), []).append(s)
    for own in tables.values():
        if len(own) == 1:
            rows = stream_df(spark, sf_dir, own[0])
        else:
            s = own[0]
            cols = ", ".join([*s.order, *(f"{x.value} AS _v{i}" for i, x in enumerate(own))])
            wide = with_ordinal(spark.sql(f"SELECT {cols} FROM {s.table} WHERE {s.where}").withColumn("_s", F.lit(s.table)), "_s", list(s.order))
            each = F.array(*[F.struct(F.lit(x.name).alias("stream_id"), F.col(f"_v{i}").alias("value")) for i, x in enumerate(own)])
            rows = wide.select("ord", F.explode(each).alias("x")).select("x.stream_id", "ord", "x.value")
        out = rows if out is None else out.unionByName(rows)
    return out


def events_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``stream_id`` = event type, with ``ts`` in microseconds and the event's id."""
    register(spark, sf_dir, ("events",))
    rows = spark.sql(f"SELECT event_type AS stream_id, event_id, value, {_US} AS ts FROM events")
    return with_ordinal(rows, "stream_id", ["ts", "event_id"])
