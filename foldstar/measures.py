"""Run times, preparation shares and differences between the two representations."""

from __future__ import annotations

import re
import time

import numpy as np


def measure(fn, warmup: int = 1, reps: int = 3) -> dict:
    for _ in range(warmup):
        fn()
    times = []
    for _ in range(reps):
        t = time.perf_counter()
        fn()
        times.append(time.perf_counter() - t)
    return {"median": float(np.median(times)), "times": times}


def compare_times(fn, joined, factored, **how) -> dict:
    """Seconds of fn on either representation, and the speed-up."""
    m, f = measure(lambda: fn(joined), **how)["median"], measure(lambda: fn(factored), **how)["median"]
    return {"seconds_m": m, "seconds_f": f, "speedup": m / f}


def per_iteration(fn, iters: int) -> float:
    """Seconds an iteration: the difference of a run of `iters` + 1 rounds and one of a single round."""
    one = measure(lambda: fn(1), 1, 1)["median"]
    more = measure(lambda: fn(iters + 1), 0, 1)["median"]
    return max(more - one, 0.0) / iters


def prep_report(prepare, learn) -> dict:
    """Seconds of preparation and of learning, and their ratio."""
    p = measure(prepare, 0, 1)["median"]
    s = measure(learn, 0, 1)["median"]
    return {"prepare": p, "learn": s, "ratio": p / s if s else float("inf")}


def difference(a, b) -> dict:
    a, b = np.asarray(a, dtype=float), np.asarray(b, dtype=float)
    gap = np.abs(a - b)
    return {"max_abs": float(gap.max(initial=0)), "max_rel": float((gap / np.maximum(np.abs(b), 1e-300)).max(initial=0)) if b.size else 0.0}


def plan_nodes(df) -> dict[str, int]:
    """How often joins, exchanges, aggregates and Python nodes stand in a frame's physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: len(re.findall(rf"\b{k}", text)) for k in ("SortMergeJoin", "BroadcastHashJoin", "ShuffledHashJoin", "CartesianProduct", "Exchange", "HashAggregate", "MapInPandas")}
