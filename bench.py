"""Headline timings: one JSON line. ``BENCH_SF_DIR``, ``BENCH_CPUS`` choose data and cores."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", str(2 * int(cpus) if cpus.isdigit() else 16))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", "file:///tmp/checkpoints").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from lattice_pages.functions import measures
    from lattice_pages.operators import codec, compare, scan
    from lattice_pages.plans import queries, streams
    from lattice_pages.session import materialize, ship

    ship(spark)
    took: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name: str, f):
        t = time.perf_counter()
        got = f()
        took[name] = round(time.perf_counter() - t, 3)
        return got

    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    names = ("li_price", "li_discount", "li_quantity", "ord_total", "ev_value", "part_price")
    src = {n: materialize(streams.stream_df(spark, sf, n), n) for n in names}
    noop(codec.encode(src["part_price"]))  # warm-up
    fast = {}
    for n in names:
        fast[n] = timed(f"encode_fast_{n}", lambda n=n: materialize(codec.encode(src[n]), "fast"))
        timed(f"decode_fast_{n}", lambda n=n: noop(codec.decode(fast[n])))
        facts[f"ratio_fast_{n}"] = round(measures.ratio(fast[n]).first().ratio, 4)
    bounded = timed("encode_bounded_ev_value", lambda: materialize(codec.encode(src["ev_value"], "bounded", eps=1e-3), "bounded"))
    timed("decode_bounded_ev_value", lambda: noop(codec.decode(bounded)))
    facts["ratio_bounded_ev_value"] = round(measures.ratio(bounded).first().ratio, 4)
    upper = timed("recompress_upper_part_price", lambda: materialize(codec.recompress(fast["part_price"]), "upper"))
    timed("decode_upper_part_price", lambda: noop(codec.decode(upper)))
    facts["ratio_upper_part_price"] = round(measures.ratio(upper).first().ratio, 4)

    rows = materialize(streams.events_by_type(spark, sf), "events")
    store = timed("store_write", lambda: materialize(codec.encode(rows), "store"))
    lo, hi = store.agg(F.min("min_ts"), F.max("max_ts")).first()
    timed("store_full_scan", lambda: noop(scan.scan_full(store)))
    timed("store_range_scan_10pct", lambda: noop(scan.scan_range(store, lo + (hi - lo) // 2, lo + (hi - lo) * 6 // 10)))
    timed("store_aggregate_stats", lambda: scan.scan_agg(store, lo + (hi - lo) // 4, lo + (hi - lo) * 3 // 4).collect())
    timed("store_aggregate_decode", lambda: scan.scan_agg(store, lo + (hi - lo) // 4, lo + (hi - lo) * 3 // 4, use_stats=False).collect())

    pages = timed("compare_codecs_ev_value", lambda: materialize(compare.run_pages(src["ev_value"], ["exact_fast", "exact_upper", "bounded", *compare.baselines.CODECS]), "compare"))
    for r in compare.summary(pages, "codec").collect():
        facts[f"core_encode_mb_s_{r.codec}"], facts[f"core_decode_mb_s_{r.codec}"], facts[f"ratio_ev_value_{r.codec}"] = round(r.encode_mb_s, 2), round(r.decode_mb_s, 2), round(r.ratio, 4)
        facts["violations"] = facts.get("violations", 0) + r.violations
    for q in ("m_residual_routed_li_price", "m_block_cost_ev_value", "o_shuffle_join", "o_rollup") if "m_residual_routed_li_price" in queries.QUERIES else ():
        timed(q, lambda q=q: noop(queries.QUERIES[q](spark, sf)))
    print(json.dumps({"metric": "codec_and_scan_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "facts": facts, "sf": sf}))


if __name__ == "__main__":
    main()
