"""Elapsed time of plans: one warm-up, then median, least and most of several runs."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame


def timed(make: Callable[[], DataFrame], reps: int = 5, warm: int = 1) -> dict[str, float]:
    """Seconds to compute all rows of a plan, without keeping or sending them."""
    spent = []
    for run in range(warm + reps):
        begin = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if run >= warm:
            spent.append(time.perf_counter() - begin)
    return {"median": median(spent), "min": min(spent), "max": max(spent), "reps": float(reps)}
