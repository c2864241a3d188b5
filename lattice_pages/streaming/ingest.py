"""Online encoding: rows of a stream in, full pages out, at most one page of state each.

State per stream: the words of the page that is being filled and its first ordinal.
Pages are emitted as soon as they are full; a page that gets no row for ``idle_ms`` is
emitted short. Rows that arrive after their page has gone out take the next ordinals
(order of arrival is the stream's order), so nothing is lost.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from lattice_pages.functions.frame import encode_page, frame
from lattice_pages.plans.profiles import PAGE, Profile, profile

PAGE_DDL = "stream_id string, page_no long, first_ord long, n int, min_ts long, max_ts long, data binary"


def encode_stream(sdf: DataFrame, profile_name: str | Profile = "exact_fast", eps: float | None = None, page_size: int = PAGE, idle_ms: int | None = None) -> DataFrame:
    """Pages of a streaming frame ``stream_id string, ts long (microseconds), value double``."""
    p = profile(profile_name, eps)

    def page(stream: str, first: int, no: int, words: np.ndarray, ts: np.ndarray) -> dict:
        return {"stream_id": stream, "page_no": no, "first_ord": first, "n": len(words), "min_ts": int(ts.min()), "max_ts": int(ts.max()), "data": frame(*encode_page(words, p)[:2])}

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        first, no, held, held_ts = state.get if state.exists else (0, 0, b"", b"")
        words, ts = np.frombuffer(held, "<i8"), np.frombuffer(held_ts, "<i8")
        out = []
        if state.hasTimedOut:
            out = [page(key[0], first, no, words, ts)] if len(words) else []
            state.update((first + len(words), no + 1, b"", b""))
            yield pd.DataFrame(out, columns=[c.split()[0] for c in PAGE_DDL.split(", ")])
            return
        new = [f.sort_values("ts", kind="stable") for f in frames]
        words = np.concatenate([words, *(f["value"].to_numpy(np.float64).view(np.int64) for f in new)])
        ts = np.concatenate([ts, *(f["ts"].to_numpy(np.int64) for f in new)])
        while len(words) >= page_size:
            out.append(page(key[0], first, no, words[:page_size], ts[:page_size]))
            words, ts, first, no = words[page_size:], ts[page_size:], first + page_size, no + 1
        state.update((first, no, words.astype("<i8").tobytes(), ts.astype("<i8").tobytes()))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame(out, columns=[c.split()[0] for c in PAGE_DDL.split(", ")])

    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_ms is not None else GroupStateTimeout.NoTimeout
    return sdf.select("stream_id", "ts", "value").groupBy("stream_id").applyInPandasWithState(run, PAGE_DDL, "first long, no long, words binary, ts binary", "append", timeout)


def windowed(sdf: DataFrame, ts_col: str, value_col: str, size: str, slide: str | None = None, late: str | None = "10 minutes") -> DataFrame:
    """Counts and extremes in event-time windows; rows later than ``late`` are dropped (None: a watermark is set already)."""
    from pyspark.sql import functions as F

    w = F.window(ts_col, size, slide) if slide else F.window(ts_col, size)
    return (sdf.withWatermark(ts_col, late) if late else sdf).groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.min(value_col).alias("lo"), F.max(value_col).alias("hi")).select("w.start", "w.end", "n", "lo", "hi")


def interval_join(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, within: str, late: str = "10 minutes") -> DataFrame:
    """Pairs of the two streams with one key and right within ``within`` after left."""
    from pyspark.sql import functions as F

    a, b = left.withWatermark(left_ts, late).alias("a"), right.withWatermark(right_ts, late).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} AND b.{right_ts} >= a.{left_ts} AND b.{right_ts} <= a.{left_ts} + INTERVAL {within}"))


def dedup(sdf: DataFrame, keys: list[str], ts_col: str, late: str = "10 minutes") -> DataFrame:
    return sdf.withWatermark(ts_col, late).dropDuplicatesWithinWatermark(keys)
