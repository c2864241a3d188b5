"""What a plan does to one page, value by value."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from lattice_pages.plans.planner import RAW, plan_page
from lattice_pages.plans.profiles import Profile, profile


def magnitude_bits(u: np.ndarray) -> int:
    """Binary digits of the magnitudes of hold residuals, without signs and anchors."""
    return sum(abs(int(d)).bit_length() for d in np.diff(u))


def explain_page(spark: SparkSession, values: list[float], profile_name: str | Profile = "exact_upper", eps: float | None = None) -> DataFrame:
    """``pos, value, lane, descriptor, coordinate, residual`` of every value under the plan chosen for it."""
    x = np.array(values, np.float64)
    plan = plan_page(x.view(np.int64), profile(profile_name, eps))
    rows, last = [], {}
    for i, k in enumerate(plan.route.tolist()):
        if k == RAW:
            rows.append((i, float(x[i]), None, "raw", None, None))
            continue
        u = int(plan.lanes[k].u[i])
        rows.append((i, float(x[i]), k, str(plan.lanes[k].desc), u, u - last[k] if k in last else None))
        last[k] = u
    return spark.createDataFrame(rows, "pos int, value double, lane int, descriptor string, coordinate long, residual long")
