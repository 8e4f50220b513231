"""Near-duplicate vectors by an epsilon grid order join.

Cosine at least c means that unit vectors are within eps = sqrt(2 - 2c). Unit vectors are projected on
their leading principal dimensions and sorted by grid cells of side eps, then by coordinates. The
sorted sequence is cut into blocks of fixed size and tiles of a few blocks. Pairs of intervals of the
sequence are halved again and again, in Spark tables down to tiles and inside a task down to leaves,
and left as soon as their boxes are further apart than eps in the projection, which never lengthens a
distance. Only leaves that stay are compared, in double precision.

Equal vectors form one class, so a vector that a third of the rows hold is one row of the join. A
joined pair of blocks emits a sum of links for each class and a spanning forest, never all links.
A block travels once for each near pair of its tile; a task holds one tile and streams the other. The
driver sees counts of ranges only, never blocks or pairs.

Defined cases: a vector that is null, empty, zero, or has null or non-finite components links with
nothing, and so does a row with a null id; vectors of different lengths never link; repeated rows
count as vectors of their own; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.graph import Forest, components
from foldstar.llm.shared import partitions, ship, stored, table

LEADING = 6
BLOCK_ROWS = 2048
#: Blocks of a tile, as far as a tile's vectors stay within TILE_BYTES.
TILE_BLOCKS = 8
TILE_BYTES = 64 << 20
LEAF = 256
SLACK = 1e-9


def _usable(v) -> F.Column:
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return v.isNotNull() & (F.size(v) > 0) & F.coalesce(finite & F.exists(v, lambda x: x != 0), F.lit(False))


def _matrix(column, dim: int) -> np.ndarray:
    return np.concatenate([np.asarray(x, dtype=np.float64) for x in column]).reshape(-1, dim)


def _unit(m: np.ndarray) -> np.ndarray:
    m = m / np.abs(m).max(axis=1, keepdims=True)
    return m / np.linalg.norm(m, axis=1, keepdims=True)


def principal(classes: DataFrame, dim: int, leading: int) -> np.ndarray:
    """Leading principal directions of all unit vectors, one column each (dim x leading)."""

    def sums(frames):
        s = np.zeros((dim + 1, dim + 1))
        for f in frames:
            u = _unit(_matrix(f["v"], dim))
            u = np.hstack([u, np.ones((len(u), 1))])
            s += u.T @ u
        yield pd.DataFrame({"i": np.arange(s.size), "x": s.ravel()})

    parts = classes.select("v").mapInPandas(sums, "i int, x double")
    got = parts.groupBy("i").agg(F.sum("x").alias("x")).toPandas()  # (dim + 1)^2 rows
    s = np.zeros((dim + 1) ** 2)
    s[got["i"]] = got["x"]
    s = s.reshape(dim + 1, dim + 1)
    n = max(s[-1, -1], 1)
    mean = s[:-1, -1] / n
    _, vectors = np.linalg.eigh(s[:-1, :-1] / n - np.outer(mean, mean))
    return vectors[:, ::-1][:, :leading].copy()


def _blocks(classes: DataFrame, dim: int, directions: np.ndarray, eps: float, rows: int, count: int) -> tuple[DataFrame, int]:
    """One row per block: block (its place), nodes, sizes, raw vectors (bytes), and the box lo, hi; and how many."""
    p = directions.shape[1]

    @F.pandas_udf("array<double>")
    def project(v: pd.Series) -> pd.Series:
        return pd.Series(list(_unit(_matrix(v, dim)) @ directions))

    placed = classes.select("*", project("v").alias("x"))
    cells = [F.floor(F.col("x")[i] / eps) for i in range(p)]
    keys = [*cells, *[F.col("x")[i] for i in range(p)], F.col("node")]
    ranges = max(1, min(partitions(classes), count // rows))
    ordered = placed.repartitionByRange(ranges, *keys).sortWithinPartitions(*keys)

    def cut(frames):
        held, n = [], 0
        for f in frames:
            while len(f):
                part = f.iloc[: rows - n]
                f = f.iloc[rows - n :]
                held.append(part)
                n += len(part)
                if n == rows:
                    yield packed(pd.concat(held))
                    held, n = [], 0
        if held:
            yield packed(pd.concat(held))

    def packed(f):
        x = np.stack(f["x"].to_list())
        return pd.DataFrame({
            "node": [f["node"].to_numpy(dtype=np.int64).tobytes()], "n": [f["n"].to_numpy(dtype=np.int64).tobytes()],
            "v": [_matrix(f["v"], dim).astype(np.float32 if single else np.float64).tobytes()],
            "x": [x.tobytes()], "lo": [x.min(axis=0)], "hi": [x.max(axis=0)],
        })

    single = classes.schema["v"].dataType.elementType.simpleString() == "float"
    made = ordered.mapInPandas(cut, "node binary, n binary, v binary, x binary, lo array<double>, hi array<double>")
    cuts = stored(made.withColumn("at", F.monotonically_increasing_id()), "blocks")
    # places in the whole sequence: the number of a range is in the upper bits of `at`, and only counts come here
    base, n = [], 0
    for r in cuts.groupBy(F.shiftright("at", 33).alias("p")).count().orderBy("p").collect():
        base.append((r["p"], n))
        n += r["count"]
    known = classes.sparkSession.createDataFrame(base, "p long, first long")
    place = (F.col("first") + F.col("at").bitwiseAND(F.lit((1 << 33) - 1))).alias("block")
    return cuts.join(F.broadcast(known), F.shiftright("at", 33) == F.col("p")).select(place, "node", "n", "v", "x", "lo", "hi"), n


def _near(lo_a, hi_a, lo_b, hi_b, eps: float) -> bool:
    gap = np.maximum(0, np.maximum(lo_a - hi_b, lo_b - hi_a))
    return float(gap @ gap) <= (eps + SLACK) ** 2


def near_tiles(boxes: DataFrame, count: int, width: int, eps: float) -> DataFrame:
    """Pairs a <= b of tiles whose boxes are near, by halving pairs of intervals of the sequence level by level.

    boxes: tile, lo, hi for tiles 0 to count - 1. A level is one row an interval; its boxes are joined to the pairs.
    """
    spark = boxes.sparkSession
    box = [*[F.min(F.col("lo")[i]).alias(f"l{i}") for i in range(width)], *[F.max(F.col("hi")[i]).alias(f"h{i}") for i in range(width)]]
    tiles = stored(boxes.groupBy("tile").agg(F.array(*box[:width]).alias("lo"), F.array(*box[width:]).alias("hi")), "tiles")
    pairs = spark.createDataFrame([(0, 0)], "a long, b long")
    for level in range(max(count - 1, 0).bit_length() - 1, -1, -1):
        size = 1 << level
        at = F.floor(F.col("tile") / size).cast("long").alias("i")
        part = tiles.groupBy(at).agg(F.array(*box[:width]).alias("lo"), F.array(*box[width:]).alias("hi")) if level else tiles.select(F.col("tile").alias("i"), "lo", "hi")
        halves = [F.struct((2 * F.col("a") + x).alias("a"), (2 * F.col("b") + y).alias("b")) for x in (0, 1) for y in (0, 1)]
        child = pairs.select(F.explode(F.array(*halves)).alias("c")).select("c.a", "c.b").where("a <= b")
        met = child.join(part.select(F.col("i").alias("a"), F.col("lo").alias("la"), F.col("hi").alias("ha")), "a").join(part.select(F.col("i").alias("b"), F.col("lo").alias("lb"), F.col("hi").alias("hb")), "b")
        gaps = [F.greatest(F.lit(0.0), F.col("la")[i] - F.col("hb")[i], F.col("lb")[i] - F.col("ha")[i]) for i in range(width)]
        apart = sum((g * g for g in gaps[1:]), gaps[0] * gaps[0])
        pairs = stored(met.where(apart <= (eps + SLACK) ** 2).select("a", "b"), "tile-pairs")
    return pairs


def _leaves(xa, xb, same: bool, eps: float):
    """Index intervals (a, b, c, d) of two blocks that may hold close pairs."""
    todo = [(0, len(xa), 0, len(xb))]
    while todo:
        a, b, c, d = todo.pop()
        if same and c < a or not _near(xa[a:b].min(axis=0), xa[a:b].max(axis=0), xb[c:d].min(axis=0), xb[c:d].max(axis=0), eps):
            continue
        if b - a <= LEAF and d - c <= LEAF:
            yield a, b, c, d
        elif same and a == c and b == d:
            m = (a + b) // 2
            todo += [(a, m, a, m), (a, m, m, b), (m, b, m, b)]
        elif b - a >= d - c:
            m = (a + b) // 2
            todo += [(a, m, c, d), (m, b, c, d)]
        else:
            m = (c + d) // 2
            todo += [(a, b, c, m), (a, b, m, d)]


def _joined(dim: int, cosine: float, eps: float, leading: int, single: bool):
    kind = np.float32 if single else np.float64

    def load(raw):
        v = np.frombuffer(raw, dtype=kind).astype(np.float64).reshape(-1, dim)
        v = v / np.abs(v).max(axis=1, keepdims=True)
        return v, np.sqrt((v * v).sum(axis=1))

    def one(p, q):
        """Links between two blocks (or inside one): class, a class of its component, sum of links."""
        same = p is q
        (va, la, xa, na, ma), (vb, lb, xb, nb, mb) = p, q
        shift = 0 if same else len(va)
        sums = np.zeros(shift + len(vb), dtype=np.int64)
        forest = Forest(len(sums))
        for a, b, c, d in _leaves(xa, xb, same, eps):
            i, j = np.nonzero((va[a:b] @ vb[c:d].T) / (la[a:b, None] * lb[None, c:d]) >= cosine)
            i, j = i + a, j + c
            if same:
                keep = i < j
                i, j = i[keep], j[keep]
            np.add.at(sums, i, nb[j])
            np.add.at(sums, j + shift, na[i])
            forest.add(i, j + shift)
        nodes = ma if same else np.concatenate([ma, mb])
        hit = np.flatnonzero(sums)
        return pd.DataFrame({"a": nodes[hit], "b": nodes[forest.up[hit]], "n": sums[hit]}) if len(hit) else None

    def run(frames):
        now, held = None, []
        for f in frames:
            for r in f.itertuples(index=False):
                if (r.a, r.b) != now:
                    now, held = (r.a, r.b), []
                v, l = load(r.v)
                block = (v, l, np.frombuffer(r.x).reshape(-1, leading), np.frombuffer(r.n, dtype=np.int64), np.frombuffer(r.node, dtype=np.int64))
                if r.side == 0:
                    held.append(block)
                # within one tile a block meets itself and those before it; the other tile's blocks meet all held ones
                for other in held if r.a == r.b or r.side == 1 else []:
                    got = one(other, block)
                    if got is not None:
                        yield got

    return run


def _linked(classes: DataFrame, dim: int, cosine: float, leading: int) -> DataFrame:
    """Columns a, b, n: class a has n links to other classes by one pair of blocks, and b is in its component."""
    spark = classes.sparkSession
    eps = float(np.sqrt(max(0.0, 2 - 2 * cosine)))
    leading = min(leading, dim)
    directions = principal(classes, dim, leading)
    count = classes.count()
    blocks, n = _blocks(classes, dim, directions, eps, BLOCK_ROWS, count)
    if not n:
        return spark.createDataFrame([], "a long, b long, n long")
    per = max(1, min(TILE_BLOCKS, TILE_BYTES // (8 * dim * BLOCK_ROWS)))
    blocks = blocks.withColumn("tile", F.floor(F.col("block") / per).cast("long"))
    pairs = near_tiles(blocks.select("tile", "lo", "hi"), -(-n // per), leading, eps)
    sides = [pairs.select("a", "b", F.lit(0).alias("side"), F.col("a").alias("tile")), pairs.where("a < b").select("a", "b", F.lit(1).alias("side"), F.col("b").alias("tile"))]
    met = sides[0].unionByName(sides[1]).join(blocks.select("tile", "block", "node", "n", "v", "x"), "tile")
    dealt = met.repartition(4 * partitions(classes), "a", "b").sortWithinPartitions("a", "b", "side", "block")
    single = classes.schema["v"].dataType.elementType.simpleString() == "float"
    return dealt.mapInPandas(_joined(dim, cosine, eps, leading, single), "a long, b long, n long")


def near_vectors(df: DataFrame, key: str = "vec_id", vector: str = "embedding", cosine: float = 0.95, leading: int = LEADING) -> DataFrame:
    """Per row of `df`: _k, n_links, component_id, kept."""
    ship(df.sparkSession)
    rows = df.select(F.col(f"`{key}`").cast("long").alias("_k"), F.col(f"`{vector}`").alias("v"))
    ok = F.col("_k").isNotNull() & _usable(F.col("v"))
    good, rest = rows.where(ok), rows.where(~F.coalesce(ok, F.lit(False)))
    grouped = good.groupBy("v").agg(F.min("_k").alias("rep"), F.count("*").alias("n"))
    classes = stored(grouped.withColumn("node", F.monotonically_increasing_id()), "vectors")
    found = None
    for (dim,) in classes.select(F.size("v")).distinct().collect():
        part = _linked(classes.where(F.size("v") == dim), dim, cosine, leading)
        found = part if found is None else found.unionByName(part)
    if found is None:
        found = df.sparkSession.createDataFrame([], "a long, b long, n long")
    found = stored(found, "vector-links")
    roots = components(found.select("a", "b"))
    sums = found.groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("other"))
    placed = classes.join(sums, "node", "left").join(roots, "node", "left").select("v", "rep", "n", F.coalesce("other", F.lit(0)).alias("other"), F.coalesce("root", "node").alias("root"))
    named = placed.groupBy("root").agg(F.min("rep").alias("component_id"))
    by_class = placed.join(named, "root").select("v", (F.col("n") - 1 + F.col("other")).alias("n_links"), "component_id")
    linked = good.join(by_class, "v").select("_k", "n_links", "component_id")
    return linked.unionByName(rest.select("_k", F.lit(0).cast("long").alias("n_links"), F.col("_k").alias("component_id"))).withColumn("kept", F.coalesce(F.col("_k") == F.col("component_id"), F.lit(True)))


def op3_vectors(spark, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings")).withColumnRenamed("_k", "vec_id")


OP3_SQL = """
WITH RECURSIVE v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings),
p AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.95),
r(a, b) AS (SELECT vec_id, vec_id FROM v UNION SELECT r.a, p.b FROM r JOIN p ON r.b = p.a),
c AS (SELECT a AS vec_id, min(b) AS component_id FROM r GROUP BY a),
n AS (SELECT a AS vec_id, count(*) AS n FROM p GROUP BY a)
SELECT vec_id, coalesce(n.n, 0)::BIGINT AS n_links, component_id, vec_id = component_id AS kept FROM c LEFT JOIN n USING (vec_id)"""
