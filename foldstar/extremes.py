"""Least and greatest products of rows with all rows, by way of the corners of their convex hulls."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a class from which on the corners are reduced for the class, and levels up to which that pays.
FEW, LEVELS = 64, 64
#: Rows that a task sorts by class at once, and products that it holds.
CHUNK, CELLS = 1 << 18, 1 << 17


def _tools():
    """Functions for tasks: shipped by value with what uses them."""

    def hull(u, v):
        """Positions of points among which are all corners of the hull of (u, v); a point within rounding of an edge may stay."""
        n = len(u)
        if n <= 3:
            return np.arange(n)
        if n > 64:  # points strictly inside the octagon of the extremes are no corners
            far = np.unique([f(w) for w in (u, v, u + v, u - v) for f in (np.argmin, np.argmax)])
            x, y = u[far] - u[far].mean(), v[far] - v[far].mean()
            far = far[np.argsort(np.arctan2(y, x))]
            a, b = u[far], v[far]
            inside = np.ones(n, dtype=bool)
            for x0, y0, x1, y1 in zip(a, b, np.roll(a, -1), np.roll(b, -1)):
                inside &= (x1 - x0) * (v - y0) - (y1 - y0) * (u - x0) > 1e-9 * (abs(x1 - x0) + abs(y1 - y0)) * (np.abs(v - y0) + np.abs(u - x0))
            left = np.flatnonzero(~inside)
        else:
            left = np.arange(n)
        left = left[np.lexsort((v[left], u[left]))]
        x, y = u[left].tolist(), v[left].tolist()

        def chain(order):
            out = []
            for i in order:
                while len(out) > 1:
                    p, q = out[-2], out[-1]
                    s, t = (x[q] - x[p]) * (y[i] - y[p]), (y[q] - y[p]) * (x[i] - x[p])
                    if s - t > -1e-9 * (abs(s) + abs(t)) and (x[q], y[q]) != (x[i], y[i]):
                        break
                    out.pop()
                out.append(i)
            return out

        return left[np.unique(chain(range(len(x))) + chain(range(len(x) - 1, -1, -1)))]

    def by_class(x):
        """Positions of rows of x (class columns, then two) that keep the corners of each class."""
        r = x[:, :-2]
        order = np.lexsort(r.T) if r.shape[1] else np.arange(len(x))
        edge = np.flatnonzero((r[order][1:] != r[order][:-1]).any(axis=1)) + 1
        return np.concatenate([part[hull(x[part, -2], x[part, -1])] for part in np.split(order, edge)]) if len(x) else np.zeros(0, dtype=int)

    return hull, by_class


def classes(frame: DataFrame, rest: list[str], most: int) -> tuple[np.ndarray, np.ndarray] | None:
    """The distinct rows of `frame` in the columns `rest`, by their hash (see `label`); None if they are too many or not finite."""
    got = frame.select(label(rest), *[F.col(f"`{c}`").cast("double").alias(f"c{i}") for i, c in enumerate(rest)]).distinct().limit(most + 1).toPandas().sort_values("h")
    h, x = got["h"].to_numpy(dtype=np.int64), got.drop(columns="h").to_numpy(dtype=float)
    if len(h) > most or not np.isfinite(x).all() or (h[1:] == h[:-1]).any():
        return None
    return h, x


def label(rest: list[str]):
    return (F.xxhash64(*[F.col(f"`{c}`").cast("double") for c in rest]) if rest else F.lit(0).cast("long")).alias("h")


def _cutter(hashes: list[np.ndarray]):
    """A function for tasks that cuts their frames into chunks; shipped by value, too."""
    most = CHUNK

    def chunks(frames):
        """Frames with h0, h1, ... as tuples of arrays of so many rows at least: class numbers, sorted, the rows' order, u, v, ids; borders of the classes."""
        held, rows = [], 0

        def whole():
            f = pd.concat(held)
            k = np.zeros(len(f), dtype=np.int64)
            for i, h in enumerate(hashes):
                k = k * len(h) + np.searchsorted(h, f[f"h{i}"].to_numpy())
            order = np.argsort(k, kind="stable")
            k, u, v = k[order], f["u"].to_numpy(dtype=float)[order], f["v"].to_numpy(dtype=float)[order]
            edge = np.flatnonzero(k[1:] != k[:-1]) + 1
            return k, u, v, f["id"].to_numpy()[order], [0, *edge.tolist()], [*edge.tolist(), len(k)]

        for f in frames:
            held, rows = [*held, f] if len(f) else held, rows + len(f)
            if rows >= most:
                yield whole()
                held, rows = [], 0
        if rows:
            yield whole()

    return chunks


def corners(rows: DataFrame, hashes: list[np.ndarray], width: int, most: int) -> pd.DataFrame | None:
    """Per class k its rows n and arrays u, v with all corners of its hull; None if they are too many or not finite.

    rows: id, u, v and h0, h1, ..., the hashes whose places in `hashes` number the class.
    """
    (hull, _), chunks = _tools(), _cutter(hashes)
    kind = "k long, n long, u array<double>, v array<double>"
    none = pd.DataFrame({"k": [-1], "n": [0], "u": [[]], "v": [[]]})

    def run(frames):
        for k, u, v, _, start, end in chunks(frames):
            keep = [s + hull(u[s:e], v[s:e]) for s, e in zip(start, end)] if np.isfinite(u).all() and np.isfinite(v).all() else None
            if keep is None or sum(map(len, keep)) * width > most:
                yield none
                return
            yield pd.DataFrame({"k": k[start], "n": np.subtract(end, start), "u": [u[x] for x in keep], "v": [v[x] for x in keep]})

    def merged(frames):
        for f in frames:
            out = []
            for k, n, us, vs in zip(f["k"], f["n"], f["us"], f["vs"]):
                u, v = np.concatenate(list(us)), np.concatenate(list(vs))
                x = hull(u, v)
                out.append((k, n, u[x], v[x]))
            yield pd.DataFrame(out, columns=["k", "n", "u", "v"])

    first = rows.mapInPandas(run, kind).groupBy("k").agg(F.sum("n").alias("n"), F.collect_list("u").alias("us"), F.collect_list("v").alias("vs"))
    got = first.mapInPandas(merged, kind).limit(most // width + 1).toPandas()
    if len(got) > most // width or (got["k"] < 0).any() or got["u"].map(len).sum() * width > most:
        return None
    return got.sort_values("k", ignore_index=True)


def met(rows: DataFrame, parts: list[tuple[np.ndarray, np.ndarray]], found: pd.DataFrame, on: str, kind: str) -> DataFrame:
    """Columns `on`, n, smallest, largest of the products of each row with the rows `found`, a class of rows at a time.

    For a class only those corners are met that are corners of the rows with the same product in the class columns.
    """
    spark = rows.sparkSession
    hashes, n = [h for h, _ in parts], int(found["n"].sum())
    chunks = _cutter(hashes)
    number = found["k"].to_numpy(dtype=np.int64)
    at = np.unravel_index(number, [len(h) for h in hashes]) if len(number) else [number] * len(parts)
    x = np.concatenate([c[i] for (_, c), i in zip(parts, at)], axis=1)
    of = np.repeat(np.arange(len(number)), found["u"].map(len).to_numpy(dtype=np.int64))
    flat = lambda c: np.concatenate([np.zeros(0), *found[c]])
    sent = spark.sparkContext.broadcast((number, x, of, flat("u"), flat("v")))
    hull, _ = _tools()
    levels, cells = LEVELS, CELLS

    def fewer(frames):
        _, x, of, u, v = sent.value
        for f in frames:
            kept = []
            for i in f["i"]:
                base, level = np.unique(x @ x[i], return_inverse=True)
                if len(base) > levels:
                    kept.append(None)
                    continue
                order = np.argsort(level[of], kind="stable")
                groups = np.split(order, np.flatnonzero(np.diff(level[of][order])) + 1)
                kept.append(np.concatenate([g[hull(u[g], v[g])] for g in groups]).astype(np.int32))
            yield pd.DataFrame({"i": f["i"], "keep": kept})

    many = np.flatnonzero(found["n"].to_numpy() >= FEW)
    keep = {}
    if len(many):
        todo = spark.createDataFrame(pd.DataFrame({"i": many})).repartition(4 * spark.sparkContext.defaultParallelism)
        got = todo.mapInPandas(fewer, "i long, keep array<int>").toPandas()
        keep = {i: k for i, k in zip(got["i"], got["keep"]) if k is not None}
    kept = spark.sparkContext.broadcast(keep)

    def run(frames):
        number, x, of, u, v = sent.value
        known = {}

        def against(k):
            if k not in known:
                i = int(np.searchsorted(number, k))
                some = kept.value.get(i, slice(None))
                known[k] = (x @ x[i])[of[some]], u[some], v[some]
            return known[k] if len(known[k][0]) < len(of) else known.pop(k)  # all corners are not held for each class

        for k, a, b, ids, start, end in chunks(frames):
            low, high = np.empty(len(k)), np.empty(len(k))
            for s, e in zip(start, end):
                base, p, q = against(int(k[s]))
                step = max(1, cells // len(base))
                for i in range(s, e, step):
                    j = slice(i, min(i + step, e))
                    g = np.multiply.outer(a[j], p)
                    g += base
                    g += np.multiply.outer(b[j], q)
                    low[j], high[j] = g.min(axis=1), g.max(axis=1)
            yield pd.DataFrame({on: ids, "n": n, "smallest": low, "largest": high})

    return rows.mapInPandas(run, f"`{on}` {kind}, n long, smallest double, largest double")
