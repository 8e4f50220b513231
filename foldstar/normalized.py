"""The factored matrix: rows with their own features and links to blocks that hold each target once.

A link is a column of the row frame. Multiplying by the 0/1 link matrix is a join of a narrow score
table (`look`); multiplying by its transpose is a group-by sum (`fold`); its Gram matrix is a count
(`hits`). Key joins, stars and joins by a pair index differ only in what the row frame is: the entity
table with features of its own, or the index with one link for each side and no features.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar import dense
from foldstar.lineage import cut
from foldstar.matrix import Matrix, RowMatrix
from foldstar.pairs import ChainIndex


#: Columns of a sparse block whose Gram a task keeps as an array (200 MB).
DENSE_WIDTH = 5_000


def _met(frame: DataFrame, on: str, block: Wide | Coo) -> DataFrame:
    """`frame` joined with a block's cells on its column `on`; the block's key comes as `_key`."""
    cells = block.df.withColumnRenamed(block.key, "_key")
    return frame.join(cells, frame[on] == cells["_key"])


@dataclass
class Wide:
    """A block with one numeric column per feature."""

    df: DataFrame
    key: str
    names: list[str]

    def __post_init__(self):
        self.df = self.df.select(F.col(f"`{self.key}`"), *[dense.d(c).alias(c) for c in self.names])

    def mapped(self, f, keeps_zero: bool) -> Wide:
        return Wide(self.df.select(F.col(f"`{self.key}`"), *[f(F.col(f"`{c}`")).cast("double").alias(c) for c in self.names]), self.key, self.names)

    def scores(self, x: np.ndarray, prefix: str) -> DataFrame:
        """key and one column per column of x: only these go through the join."""
        return self.df.select(F.col(f"`{self.key}`").alias("_key"), *[_dot(self.names, x[:, j]).alias(f"{prefix}{j}") for j in range(x.shape[1])])

    def fold_product(self, folded: DataFrame, on: str, cols: list[str]) -> np.ndarray:
        """sum over targets of features^T folded values: d_i x len(cols)."""
        return dense.products(_met(folded, on, self), self.names, cols)

    def rows_estimate(self) -> float:
        """The optimizer's guess at the number of targets; no job runs."""
        return float(self.df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) / (8 * len(self.names) + 16)

    def fold_cells(self, folded: DataFrame, on: str, cols: list[str]) -> DataFrame:
        """Rows (p, v) of features^T folded values, p = feature * len(cols) + column."""
        return dense.product_cells(_met(folded, on, self), self.names, cols)

    def gram_cells(self, hits: DataFrame, on: str, weighting: str) -> DataFrame:
        """Rows (p, v) of the Gram weighted by `_hits`, upper half at least."""
        joined, w = _met(hits, on, self), F.col("_hits").cast("double")
        if weighting == "sqrt":
            return dense.product_cells(joined.select(*[(F.sqrt(w) * F.col(f"`{n}`")).alias(n) for n in self.names]), self.names)
        return dense.product_cells(joined, self.names, weight="_hits")

    def cells(self) -> DataFrame:
        """Long form: _key, col, val without zeros."""
        cell = F.explode(F.array(*[F.struct(F.lit(i).alias("col"), F.col(f"`{c}`").alias("val")) for i, c in enumerate(self.names)])).alias("x")
        return self.df.select(F.col(f"`{self.key}`").alias("_key"), cell).select("_key", "x.col", "x.val").where("val <> 0")

    def joined(self, rows: DataFrame, on: str) -> DataFrame:
        return rows.join(self.df.withColumnRenamed(self.key, "_key"), rows[on] == F.col("_key")).drop("_key")

    def renamed(self, names: list[str]) -> Wide:
        return Wide(self.df.select(F.col(f"`{self.key}`"), *[F.col(f"`{c}`").alias(n) for c, n in zip(self.names, names)]), self.key, names)


@dataclass
class Coo:
    """A sparse block in long form: key, col (position), val; absent cells are zero."""

    df: DataFrame
    key: str
    names: list[str]
    keys: DataFrame  # every key of the block, so that rows of zeros stay rows

    def mapped(self, f, keeps_zero: bool) -> Coo:
        if not keeps_zero:
            raise ValueError("this function makes a sparse block dense; convert it first (Coo.wide)")
        return Coo(self.df.select(F.col(f"`{self.key}`"), "col", f(F.col("val")).cast("double").alias("val")), self.key, self.names, self.keys)

    def scores(self, x: np.ndarray, prefix: str) -> DataFrame:
        spark = self.df.sparkSession
        m = x.shape[1]
        table = spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(x) if np.any(r)], "_c int, " + ", ".join(f"_w{j} double" for j in range(m)))
        made = self.df.join(table, F.col("col") == F.col("_c")).groupBy(F.col(f"`{self.key}`").alias("_key")).agg(*[F.sum(F.col("val") * F.col(f"_w{j}")).alias(f"{prefix}{j}") for j in range(m)])
        every = self.keys.select(F.col(f"`{self.key}`").alias("_key"))
        return every.join(made, "_key", "left").select("_key", *[F.coalesce(f"{prefix}{j}", F.lit(0.0)).alias(f"{prefix}{j}") for j in range(m)])

    def fold_product(self, folded: DataFrame, on: str, cols: list[str]) -> np.ndarray:
        joined = _met(folded, on, self)
        got = joined.groupBy("col").agg(*[F.sum(F.col("val") * dense.d(c)).alias(f"s{i}") for i, c in enumerate(cols)]).collect()
        out = np.zeros((len(self.names), len(cols)))
        for r in got:
            out[r["col"]] = r[1:]
        return out

    def gram_long(self, hits: DataFrame, on: str) -> DataFrame:
        """i, j, value for i <= j: pairs of the non-zeros within each key; up to DENSE_WIDTH columns added up in one array a task."""
        if len(self.names) <= DENSE_WIDTH:
            return self._gram_in_arrays(hits, on)
        a = _met(hits, on, self).select(F.col("_key").alias("_k"), "_hits", F.col("col").alias("i"), F.col("val").alias("vi"))
        b = self.df.select(F.col(f"`{self.key}`").alias("_k"), F.col("col").alias("j"), F.col("val").alias("vj"))
        return a.join(b, "_k").where("i <= j").groupBy("i", "j").agg(F.sum(F.col("_hits") * F.col("vi") * F.col("vj")).alias("value"))

    def _gram_in_arrays(self, hits: DataFrame, on: str) -> DataFrame:
        """`gram_long` with a d x d array in each of a few tasks: rows of these arrays cross the shuffle, not pairs of cells."""
        d, kind = len(self.names), self.df.schema["col"].dataType.simpleString()
        cells = _met(hits, on, self).where("val is not null").groupBy("_key", "_hits").agg(F.collect_list(F.struct("col", "val")).alias("x"))
        cells = cells.select("_hits", F.col("x")["col"].alias("c"), F.col("x")["val"].alias("v"))

        def partial(frames):
            import pandas as pd

            g = np.zeros((d, d))
            for f in frames:
                for n, c, v in zip(f["_hits"], f["c"], f["v"]):
                    c, at = np.unique(c, return_inverse=True)
                    v = np.bincount(at, weights=v)
                    g[np.ix_(c, c)] += np.outer(n * v, v)
            some = np.flatnonzero(g.any(axis=1))
            for s in range(0, len(some), 256):
                yield pd.DataFrame({"i": some[s : s + 256], "x": [g[i, i:] for i in some[s : s + 256]]})

        def added(frames):
            import pandas as pd

            for f in frames:
                for i, parts in zip(f["i"], f["parts"]):
                    v = np.sum([np.asarray(p) for p in parts], axis=0)
                    hit = np.flatnonzero(v)
                    yield pd.DataFrame({"i": np.full(len(hit), i), "j": hit + i, "value": v[hit]})

        n = 2 * self.df.sparkSession.sparkContext.defaultParallelism
        rows = cells.coalesce(n).mapInPandas(partial, "i long, x array<double>")
        return rows.groupBy("i").agg(F.collect_list("x").alias("parts")).mapInPandas(added, f"i {kind}, j {kind}, value double")

    def rows_estimate(self) -> float:
        return float(self.keys._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) / 24

    def fold_cells(self, folded: DataFrame, on: str, cols: list[str]) -> DataFrame:
        c = len(cols)
        made = _met(folded, on, self).groupBy("col").agg(*[F.sum(F.col("val") * dense.d(x)).alias(f"s{i}") for i, x in enumerate(cols)])
        cell = F.explode(F.array(*[F.struct(F.lit(i).alias("j"), F.col(f"s{i}").alias("v")) for i in range(c)])).alias("x")
        return made.select("col", cell).select((F.col("col").cast("long") * c + F.col("x.j")).alias("p"), "x.v")

    def gram_cells(self, hits: DataFrame, on: str, weighting: str) -> DataFrame:
        w = len(self.names)
        return self.gram_long(hits, on).select((F.col("i").cast("long") * w + F.col("j")).alias("p"), F.col("value").alias("v"))

    def cells(self) -> DataFrame:
        return self.df.select(F.col(f"`{self.key}`").alias("_key"), "col", "val")

    def wide(self) -> Wide:
        cells = [F.coalesce(F.sum(F.when(F.col("col") == i, F.col("val"))), F.lit(0.0)).alias(c) for i, c in enumerate(self.names)]
        every = self.keys.select(F.col(f"`{self.key}`"))
        return Wide(every.join(self.df, self.key, "left").groupBy(self.key).agg(*cells), self.key, self.names)

    def joined(self, rows: DataFrame, on: str) -> DataFrame:
        return self.wide().joined(rows, on)


class KeyNames(Sequence):
    """Names of identity columns, one a key: made on demand, so that a wide block costs the driver nothing."""

    def __init__(self, key: str, n: int):
        self.key, self.n = key, n

    def __len__(self) -> int:
        return self.n

    def __getitem__(self, i):
        return [f"{self.key}#{j}" for j in range(*i.indices(self.n))] if isinstance(i, slice) else f"{self.key}#{range(self.n)[i]}"


@dataclass
class Link:
    column: str
    block: Wide | Coo


def _dot(names: list[str], w: np.ndarray):
    parts = [F.lit(float(v)) * F.col(f"`{c}`") for c, v in zip(names, w) if v != 0]
    out = parts[0] if parts else F.lit(0.0)
    for p in parts[1:]:
        out = out + p
    return out


@dataclass
class FactoredMatrix(Matrix):
    """rows: ids, link columns, own features and any other row columns (targets); never the joined features.

    index: where rows are the pairs of a join index, its tables, one a link; sums, Grams and scores need no pairs then.
    """

    rows: DataFrame
    own: list[str]
    links: list[Link]
    trace: list[str] = field(default_factory=list)
    index: ChainIndex | None = None

    # building
    @classmethod
    def star(cls, entity: DataFrame, attributes: list[tuple[DataFrame | Wide | Coo, str, str, list[str]]], own: list[str], keep: list[str] = (), total: bool = False) -> FactoredMatrix:
        """attributes: (frame, fk in entity, key, features). Rows whose key finds no target leave T, as in an inner join.

        A target key that is there twice raises: a link has one target. total=True states that every key finds
        exactly one (see validate), which spares the semi-joins and the check.
        """
        rows = entity.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*keep, *[fk for _, fk, *_ in attributes]])], *[dense.d(c).alias(c) for c in own if c not in keep])
        links = []
        for frame, fk, key, names in attributes:
            block = frame if isinstance(frame, (Wide, Coo)) else Wide(frame, key, names)
            links.append(Link(fk, block))
        out = cls(rows, list(own), links, ["star"])
        if total:
            return out
        for link in links:
            keys = (link.block.keys if isinstance(link.block, Coo) else link.block.df).select(F.col(f"`{link.block.key}`").alias("_t"))
            if not keys.groupBy("_t").count().where("count > 1").isEmpty():
                raise ValueError(f"keys of the block behind `{link.column}` repeat")
        return out.trimmed(blocks=False)

    @classmethod
    def mn(cls, left: Wide, right: Wide, left_on: DataFrame | None = None, right_on: DataFrame | None = None) -> FactoredMatrix:
        """M:N join by an explicit pair index; left_on and right_on have the key and a column `j`. Without them: all pairs, one value of `j`."""
        if left_on is None and right_on is None:
            left_on, right_on = (b.df.select(F.col(f"`{b.key}`"), F.lit(0).alias("j")) for b in (left, right))
        a = left_on.select(F.col(f"`{left.key}`").alias("_p0"), F.col("j").alias("_r0"))
        b = right_on.select(F.col(f"`{right.key}`").alias("_p1"), F.col("j").alias("_l1"))
        index = ChainIndex([a, b])
        return cls(index.rows(), [], [Link("_p0", left), Link("_p1", right)], ["pair index"], index)

    @classmethod
    def chain(cls, blocks: list[Wide], tables: list[DataFrame], conditions: list[tuple[str, str]]) -> FactoredMatrix:
        """Chain of equi-joins: conditions[i] joins column conditions[i][0] of table i to [1] of table i + 1."""
        parts = []
        for i, (block, table) in enumerate(zip(blocks, tables)):
            wanted = {f"_p{i}": block.key}
            if i < len(conditions):
                wanted[f"_r{i}"] = conditions[i][0]
            if i:
                wanted[f"_l{i}"] = conditions[i - 1][1]
            parts.append(table.select(*[F.col(f"`{c}`").alias(n) for n, c in wanted.items()]))
        index = ChainIndex(parts)
        return cls(index.rows(), [], [Link(f"_p{i}", b) for i, b in enumerate(blocks)], ["chain index"], index)

    def explicit(self) -> FactoredMatrix:
        """The same matrix over the pairs themselves: every operator makes them."""
        return FactoredMatrix(self.rows, self.own, self.links, [*self.trace, "explicit pairs"])

    def labelled(self, name: str, f) -> FactoredMatrix:
        """A row column made of a join index's keys: f(_p0, _p1, ...) by operators that Columns and arrays both have."""
        index = ChainIndex(self.index.tables, self.index.labels | {name: f})
        return FactoredMatrix(index.rows(), self.own, self.links, self.trace, index)

    def _has_index(self) -> bool:
        columns = [k.column for k in self.links]
        return self.index is not None and not self.own and len(set(columns)) == len(columns) and {*columns} <= {f"_p{i}" for i in range(len(self.index.tables))}

    def by_tables(self) -> KeyedJoin | None:
        """The same matrix as sums by join value; None without an index, or with a block that is not wide."""
        from foldstar.keyed import KeyedJoin

        if not self._has_index() or any(isinstance(k.block, Coo) for k in self.links):
            return None
        blocks, tables = {k.column: k.block for k in self.links}, []
        for i, t in enumerate(self.index.tables):
            b = blocks.get(f"_p{i}")
            tables.append((t.join(b.df.withColumnRenamed(b.key, "_key"), t[f"_p{i}"] == F.col("_key")).drop("_key") if b else t, b.names if b else []))
        return KeyedJoin(tables, [(f"_r{i}", f"_l{i + 1}") for i in range(len(tables) - 1)])

    @property
    def names(self) -> list[str]:
        return [*self.own, *[n for link in self.links for n in link.block.names]]

    def offsets(self) -> list[int]:
        out = [len(self.own)]
        for link in self.links:
            out.append(out[-1] + len(link.block.names))
        return out

    def catalog(self) -> list[tuple[str, int, str]]:
        """(block, offset, feature) for every column of T."""
        owner = ["entity"] * len(self.own) + [link.column for link in self.links for _ in link.block.names]
        return [(b, i, n) for i, (b, n) in enumerate(zip(owner, self.names))]

    def _with(self, rows=None, links=None, rule="") -> FactoredMatrix:
        same = rows is None or rows is self.rows
        return FactoredMatrix(self.rows if rows is None else rows, self.own, self.links if links is None else links, [*self.trace, rule], self.index if same else None)

    def trimmed(self, rows: bool = True, blocks: bool = True) -> FactoredMatrix:
        """Rows without a target leave T; targets that no row refers to leave their block (semi-joins).

        A look is an inner join and a fold never meets unused targets, so results do not need the
        second; it pays where a block is much larger than what the rows use.
        """
        r, links = self.rows, self.links
        if rows:
            for link in links:
                have = (link.block.keys if isinstance(link.block, Coo) else link.block.df).select(F.col(f"`{link.block.key}`").alias("_t"))
                r = r.join(have, F.col(f"`{link.column}`") == F.col("_t"), "left_semi")
        if blocks:
            links = []
            for link in self.links:
                b, used = link.block, r.select(F.col(f"`{link.column}`").alias("_t"))
                semi = lambda df, key: df.join(used, F.col(f"`{key}`") == F.col("_t"), "left_semi")  # noqa: B023, E731
                links.append(Link(link.column, Coo(semi(b.df, b.key), b.key, b.names, semi(b.keys, b.key)) if isinstance(b, Coo) else Wide(semi(b.df, b.key), b.key, b.names)))
        return self._with(r, links, "trim")

    def validate(self) -> dict[str, dict[str, int]]:
        """Per link: targets with a repeated key, and rows without a target."""
        out = {}
        for link in self.links:
            b = link.block
            keys = (b.keys if isinstance(b, Coo) else b.df).select(F.col(f"`{b.key}`").alias("_t"))
            out[link.column] = {
                "repeated": keys.groupBy("_t").count().where("count > 1").count(),
                "dangling": self.rows.join(keys, F.col(f"`{link.column}`") == F.col("_t"), "left_anti").count(),
            }
        return out

    def n_rows(self) -> int:
        return self.rows.count()

    def stats(self, cells: bool = False) -> dict:
        """n, d, non-zeros and their share, and per link targets, tuple ratio, feature ratio; size of T over size of its parts.

        Non-zeros are counted, without a join, where `cells` asks for them.
        """
        n = self.n_rows()
        parts = n * len(self.own)
        out = {"n": n, "d": self.d, "links": []}
        if cells:
            out["nnz"] = int(round(self.mapped(lambda c: (c != 0).cast("double"), True).sum()))
            out["sparsity"] = out["nnz"] / (n * self.d) if n and self.d else 0.0
        for link in self.links:
            b = link.block
            t = (b.keys if isinstance(b, Coo) else b.df).count()
            w = len(b.names)
            out["links"].append({"column": link.column, "targets": t, "width": w, "tuple_ratio": n / t if t else float("inf"), "feature_ratio": w / len(self.own) if self.own else float("inf")})
            parts += t * w
        out["redundancy"] = n * self.d / parts if parts else float("inf")
        return out

    def materialize(self):
        """The joined table: the baseline's input."""
        from foldstar.regular import RegularMatrix

        rows = self.rows
        for link in self.links:
            rows = link.block.joined(rows, link.column)
        return RegularMatrix(rows, self.names)

    def row_matrix(self, *columns: str) -> RowMatrix:
        """Columns of the row frame (targets) as n x m values."""
        names = [f"_v{i}" for i in range(len(columns))]
        return RowMatrix(self.rows.select("*", *[dense.d(c).alias(n) for c, n in zip(columns, names)]), names, self)

    def row_frame(self) -> DataFrame:
        return self.rows

    def on(self, rows: DataFrame) -> FactoredMatrix:
        """The same links and features over a frame with the same rows and more columns."""
        return FactoredMatrix(rows, self.own, self.links, self.trace)

    # closed operators
    def mapped(self, f, keeps_zero: bool) -> FactoredMatrix:
        rows = self.rows.withColumns({c: f(F.col(f"`{c}`")).cast("double") for c in self.own}) if self.own else self.rows
        return self._with(rows, [Link(k.column, k.block.mapped(f, keeps_zero)) for k in self.links], "element-wise per block")

    def __getitem__(self, names: list[str]) -> FactoredMatrix:
        """The columns of T with these names, in T's order."""
        have = set(names)
        links = []
        for k in self.links:
            keep = [c for c in k.block.names if c in have]
            if not keep:
                continue
            if isinstance(k.block, Coo):
                at = {k.block.names.index(c): i for i, c in enumerate(keep)}
                df = k.block.df.where(F.col("col").isin(list(at)))
                if at:
                    moved = F.create_map(*[F.lit(x) for p in at.items() for x in p])
                    df = df.withColumn("col", moved[F.col("col")])
                links.append(Link(k.column, Coo(df, k.block.key, keep, k.block.keys)))
            else:
                links.append(Link(k.column, Wide(k.block.df, k.block.key, keep)))
        return FactoredMatrix(self.rows, [c for c in self.own if c in have], links, [*self.trace, "columns"], self.index)

    def filter_rows(self, condition) -> FactoredMatrix:
        return self._with(self.rows.where(condition), rule="filter rows")

    def filter_block(self, i: int, condition) -> FactoredMatrix:
        """Keep rows of T whose target in block i meets the condition: a semi-join on the link."""
        k = self.links[i]
        block = Wide(k.block.df.where(condition), k.block.key, k.block.names)
        rows = self.rows.join(block.df.select(F.col(f"`{block.key}`").alias("_t")), F.col(f"`{k.column}`") == F.col("_t"), "left_semi")
        return self._with(rows, [*self.links[:i], Link(k.column, block), *self.links[i + 1 :]], "filter block")

    def hstack(self, block: Wide, column: str) -> FactoredMatrix:
        return self._with(links=[*self.links, Link(column, block)], rule="hstack")

    def vstack(self, other: FactoredMatrix) -> FactoredMatrix:
        """More rows over the same blocks."""
        return self._with(self.rows.unionByName(other.rows), rule="vstack")

    # aggregations
    def row_sums(self) -> RowMatrix:
        return self.scored(np.ones((self.d, 1)))

    def with_row_sums(self, name: str, f) -> FactoredMatrix:
        """T over a row frame with one more column: the row's sum of f(cell)."""
        frame, total = self.rows, F.lit(0.0)
        for c in self.own:
            total = total + f(F.col(f"`{c}`"))
        for i, link in enumerate(self.links):
            s = link.block.mapped(f, True).scores(np.ones((len(link.block.names), 1)), f"_n{i}_")
            frame = frame.join(s, frame[link.column] == s["_key"]).drop("_key")
            total = total + F.col(f"_n{i}_0")
        return self.on(frame.select(*[F.col(f"`{c}`") for c in self.rows.columns], total.alias(name)))

    def row_extreme(self, kind: str = "min") -> RowMatrix:
        """Least or greatest cell of each row: per block once for each target, then looked up."""
        pick = F.least if kind == "min" else F.greatest
        parts, frame = [F.col(f"`{c}`") for c in self.own], self.rows
        for i, link in enumerate(self.links):
            block = link.block.wide() if isinstance(link.block, Coo) else link.block
            cells = [F.col(f"`{c}`") for c in block.names]
            best = block.df.select(F.col(f"`{block.key}`").alias("_key"), (pick(*cells) if len(cells) > 1 else cells[0]).alias(f"_m{i}"))
            frame = frame.join(best, frame[link.column] == best["_key"]).drop("_key")
            parts.append(F.col(f"_m{i}"))
        value = pick(*parts) if len(parts) > 1 else parts[0]
        return RowMatrix(frame.select(*[F.col(f"`{c}`") for c in self.rows.columns], value.alias("_v0")), ["_v0"], self)

    def col_extreme(self, kind: str = "min") -> np.ndarray:
        """Least or greatest cell of each column: own rows, and targets that some row refers to."""
        f = F.min if kind == "min" else F.max
        get = lambda df, names: [float(x) for x in df.agg(*[f(F.col(f"`{c}`")).alias(f"s{i}") for i, c in enumerate(names)]).first()] if names else []
        out = get(self.rows, self.own)
        for link in self.trimmed(rows=False).links:
            block = link.block.wide() if isinstance(link.block, Coo) else link.block
            out += get(block.df, block.names)
        return np.array(out)

    def hits(self, i: int) -> DataFrame:
        return self.rows.groupBy(self.links[i].column).agg(F.count("*").alias("_hits"))

    def col_sums(self) -> np.ndarray:
        """T^T 1: hits of each target and own sums from one pass; by counts along the tables of a join index."""
        if (k := self.by_tables()) is not None:
            return k.col_sums()
        return self.folded(RowMatrix(self.rows.withColumn("_v0", F.lit(1.0)), ["_v0"], self))[:, 0]

    def sum(self) -> float:
        return float(self.col_sums().sum())

    # products
    def scored(self, x: np.ndarray, order: str = "score_first") -> RowMatrix:
        """T X beside the rows. order="lookup_first" joins features before scoring: the ablation."""
        if order == "lookup_first":
            return self.materialize().scored(x)
        m, off = x.shape[1], self.offsets()
        if self._has_index():
            return self._scored_by_tables(x)
        frame = self.rows
        parts = [[_dot(self.own, x[: off[0], j])] for j in range(m)]
        for i, link in enumerate(self.links):
            s = link.block.scores(x[off[i] : off[i + 1]], f"_s{i}_")
            frame = frame.join(s, frame[link.column] == s["_key"]).drop("_key")
            for j in range(m):
                parts[j].append(F.col(f"_s{i}_{j}"))
        keep = [F.col(f"`{c}`") for c in self.rows.columns if not c.startswith("_v")]
        return RowMatrix(frame.select(*keep, *[sum(p[1:], p[0]).alias(f"_v{j}") for j, p in enumerate(parts)]), [f"_v{j}" for j in range(m)], self)

    def _scored_by_tables(self, x: np.ndarray) -> RowMatrix:
        """T X for the pairs of a join index: scores meet their tables before these are joined."""
        m, off, parts = x.shape[1], self.offsets(), []
        at = {k.column: i for i, k in enumerate(self.links)}
        values = [None] * len(self.index.tables)
        for column, k in at.items():
            values[int(column[2:])] = self.links[k].block.scores(x[off[k] : off[k + 1]], f"_s{k}_")
            parts.append([F.col(f"_s{k}_{j}") for j in range(m)])
        frame = self.index.beside(values)
        keep = [F.col(f"`{c}`") for c in self.rows.columns if not c.startswith("_v")]
        return RowMatrix(frame.select(*keep, *[sum((p[j] for p in parts[1:]), parts[0][j]).alias(f"_v{j}") for j in range(m)]), [f"_v{j}" for j in range(m)], self)

    def folded_scores(self, w: np.ndarray, y: str, residual) -> np.ndarray:
        """T^T residual(T w, y): over two tables and a label of their keys pairs are met in blocks; see Matrix.folded_scores."""
        if not self._has_index() or len(self.index.tables) != 2 or [k.column for k in self.links] != ["_p0", "_p1"] or y not in self.index.labels:
            return super().folded_scores(w, y, residual)
        off = self.offsets()
        scores = [k.block.scores(np.asarray(w).reshape(-1, 1)[a:b], "_s").select("_key", F.col("_s0").alias("s")) for k, a, b in zip(self.links, off, off[1:])]
        return np.concatenate([k.block.fold_product(f, k.column, ["v"])[:, 0] for k, f in zip(self.links, self.index.folds(scores, y, residual))])

    def _folds(self, r: RowMatrix, extra: list) -> tuple[DataFrame, list[str]]:
        """One row for each target of each link column, from one pass over the rows of R.

        Columns: the link columns (null but for the target's own), _first (the first link column's targets),
        and sums over the target's rows: _fp{j} of R, _fo{k}_{j} of own features times R, _fx{i} of `extra`.
        """
        columns = list(dict.fromkeys(k.column for k in self.links))
        sums = [F.sum(v).alias(f"_fp{j}") for j, v in enumerate(r.cols)]
        sums += [F.sum(F.col(f"`{c}`") * F.col(v)).alias(f"_fo{k}_{j}") for k, c in enumerate(self.own) for j, v in enumerate(r.cols)]
        sums += [F.sum(dense.d(x)).alias(f"_fx{i}") for i, x in enumerate(extra)]
        if len(columns) == 1:
            return r.frame.groupBy(columns[0]).agg(F.lit(True).alias("_first"), *sums), columns
        sets = [F.col(f"`{c}`") for c in columns]
        return r.frame.groupingSets([[c] for c in sets], *sets).agg((F.grouping(sets[0]) == 0).alias("_first"), *sums), columns

    def folded(self, r: RowMatrix, extra: list = ()) -> np.ndarray | tuple[np.ndarray, np.ndarray]:
        """T^T R in one pass: every link's folds by one aggregate over grouping sets, then each joined with its block.

        Own features ride on the first link's folds. With `extra` (columns over R's frame) also their sums.
        """
        e, m, x = len(self.own), len(r.cols), len(extra)
        if not self.links:
            got = dense.sums(r.frame, [dense.d(c) * F.col(v) for c in self.own for v in r.cols] + list(extra))
            return (got[: e * m].reshape(e, m), got[e * m :]) if x else got.reshape(e, m)
        folds, _ = self._folds(r, extra)
        met, names, parts = folds, [], []
        for i, link in enumerate(self.links):
            if isinstance(link.block, Coo):
                continue
            cells = link.block.df.select(F.col(f"`{link.block.key}`").alias(f"_k{i}"), *[F.col(f"`{c}`").alias(f"_f{i}_{k}") for k, c in enumerate(link.block.names)])
            met = met.join(cells, F.col(f"`{link.column}`") == F.col(f"_k{i}"), "left")
            names += [f"_f{i}_{k}" for k in range(len(link.block.names))]
        sums = [f"_fp{j}" for j in range(m)]
        once = [F.when(F.col("_first"), F.col(c)) for c in [*[f"_fo{k}_{j}" for k in range(e) for j in range(m)], *[f"_fx{i}" for i in range(x)]]]
        w, tail = len(names), len(once)
        if w * m + tail <= dense.TARGET_PRODUCTS:
            got = dense.sums(met, [F.col(c) * F.col(p) for c in names for p in sums] + once)
        else:
            def partial(a):
                return np.concatenate([(a[:, :w].T @ a[:, w : w + m]).ravel(), a[:, w + m :].sum(axis=0)])

            filled = [F.coalesce(F.col(c) if isinstance(c, str) else c, F.lit(0.0)) for c in [*names, *sums, *once]]
            got = dense.gathered([(dense.flat(met, filled, partial, w * m + tail), w * m + tail)])[0]
        wide = iter(np.split(got[: w * m].reshape(w, m), np.cumsum([len(k.block.names) for k in self.links if not isinstance(k.block, Coo)])[:-1]) if w else [])
        parts = [got[w * m : w * m + e * m].reshape(e, m)]
        for link in self.links:
            parts.append(link.block.fold_product(folds.where(F.col(f"`{link.column}`").isNotNull()), link.column, sums) if isinstance(link.block, Coo) else next(wide))
        out = np.concatenate(parts)
        return (out, got[w * m + e * m :]) if x else out

    def gram(self, method: str = "efficient", weighting: str = "direct", pairs: str = "hybrid") -> np.ndarray:
        """T^T T by blocks, all in one query.

        Own features directly. A link's aggregate counts hits and sums own features: joined with its block, it
        gives the block's weighted Gram and its products with own features. Two links: pairs="hybrid" looks one
        block up and folds it along the link with fewer targets; "cooc" counts pairs of targets first.
        method="naive": linked diagonal blocks through an explicit product of the link with itself.
        """
        off, out, e = self.offsets(), np.zeros((self.d, self.d)), len(self.own)
        if self.d > dense.MAX_WIDTH:
            raise ValueError(f"{self.d} columns are too many for the driver; use gram_long")
        if weighting == "direct" and pairs == "hybrid" and (k := self.by_tables()) is not None:
            got = k.gram(diagonal=method != "naive")
            for a, b, link in zip(off, off[1:], self.links) if method == "naive" else ():
                got[a:b, a:b] = dense.mirrored(dense.gathered([(self._naive_cells(link), (b - a) ** 2)])[0].reshape(b - a, b - a))
            return got
        part = [slice(0, e), *[slice(a, b) for a, b in zip(off, off[1:])]]
        pieces = [(dense.product_cells(self.rows, self.own), 0, 0)] if e else []
        for i, link in enumerate(self.links, 1):
            folded = self.rows.groupBy(link.column).agg(F.count("*").alias("_hits"), *[F.sum(F.col(f"`{c}`")).alias(f"_e{k}") for k, c in enumerate(self.own)])
            pieces.append((self._naive_cells(link) if method == "naive" else link.block.gram_cells(folded.select(link.column, "_hits"), link.column, weighting), i, i))
            if e:
                pieces.append((link.block.fold_cells(folded, link.column, [f"_e{k}" for k in range(e)]), i, 0))
        for i in range(len(self.links)):
            for j in range(i + 1, len(self.links)):
                cells, a, b = self._cross_cells(i, j, pairs)
                pieces.append((cells, a + 1, b + 1))
        width = lambda x: part[x].stop - part[x].start
        for (_, a, b), got in zip(pieces, dense.gathered([(f, width(a) * width(b)) for f, a, b in pieces])):
            got = got.reshape(width(a), width(b))
            out[part[a], part[b]] = dense.mirrored(got) if a == b else got
            out[part[b], part[a]] = out[part[a], part[b]].T
        return out

    def _naive_cells(self, link: Link) -> DataFrame:
        moved = _met(self._link_product(link), "_a", link.block).groupBy("_b").agg(*[F.sum(F.col("_c") * F.col(f"`{c}`")).alias(f"_m{j}") for j, c in enumerate(link.block.names)])
        return link.block.fold_cells(moved, "_b", [f"_m{j}" for j in range(len(link.block.names))])

    def gram_long(self) -> DataFrame:
        """T^T T as rows (i, j, value), i <= j by position, zeros absent: for widths that no driver holds.

        Blocks meet cell by cell. Links meet through counts of their pairs of targets, so the work is bounded
        by pairs of non-zeros in a row of T.
        """
        off = self.offsets()
        frames = []
        for i, c in enumerate(self.own):
            frames.append(self.rows.agg(*[F.sum(F.col(f"`{c}`") * F.col(f"`{x}`")).alias(f"s{j}") for j, x in enumerate(self.own) if j >= i]).select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"s{j}").alias("value")) for j in range(i, len(self.own))])).alias("x")).select("x.*"))
        cells = [k.block.cells().select(F.col("_key"), (F.col("col") + off[i]).alias("col"), "val") for i, k in enumerate(self.links)]
        for i, k in enumerate(self.links):
            folded = self.rows.groupBy(F.col(f"`{k.column}`").alias("_key")).agg(F.count("*").alias("_hits"), *[F.sum(F.col(f"`{c}`")).alias(f"_e{n}") for n, c in enumerate(self.own)])
            a, b = cells[i].select("_key", F.col("col").alias("i"), F.col("val").alias("x")), cells[i].select("_key", F.col("col").alias("j"), F.col("val").alias("y"))
            frames.append(folded.select("_key", "_hits").join(a, "_key").join(b, "_key").where("i <= j").select("i", "j", (F.col("_hits") * F.col("x") * F.col("y")).alias("value")))
            if self.own:
                own = F.explode(F.array(*[F.struct(F.lit(n).alias("i"), F.col(f"_e{n}").alias("x")) for n in range(len(self.own))])).alias("e")
                frames.append(folded.select("_key", own).select("_key", "e.i", "e.x").join(b, "_key").select("i", "j", (F.col("x") * F.col("y")).alias("value")))
            for j in range(i + 1, len(self.links)):
                both = self.cooc(i, j)
                u, v = cells[i].toDF("_a", "i", "x"), cells[j].toDF("_b", "j", "y")
                frames.append(both.join(u, "_a").join(v, "_b").select("i", "j", (F.col("_c") * F.col("x") * F.col("y")).alias("value")))
        long = frames[0].select(F.col("i").cast("long"), F.col("j").cast("long"), "value")
        for f in frames[1:]:
            long = long.unionByName(f.select(F.col("i").cast("long"), F.col("j").cast("long"), "value"))
        return long.groupBy("i", "j").agg(F.sum("value").alias("value")).where("value <> 0")

    def _link_product(self, link: Link) -> DataFrame:
        """K^T K as (target, target, count) by an explicit product: K with itself on row numbers, though it is diagonal.

        The rows of a join index are those of the link's table, each as often as its partners say: K is the
        link of that table, repeated, so its product is that of the table's link weighted by the repeats.
        """
        if (k := self.by_tables()) is not None:
            i = int(link.column[2:])
            r = cut(k.weighted(i).select(F.monotonically_increasing_id().alias("_r"), F.col(link.column).alias("_a"), F.col("_w").cast("long").alias("_w")), "numbered")
            return r.join(r.select("_r", F.col("_a").alias("_b")), "_r").groupBy("_a", "_b").agg(F.sum("_w").alias("_c"))
        r = cut(self.rows.select(F.monotonically_increasing_id().alias("_r"), F.col(f"`{link.column}`").alias("_a")), "numbered")
        return r.join(r.withColumnRenamed("_a", "_b"), "_r").groupBy("_a", "_b").agg(F.count("*").alias("_c"))

    def cooc(self, i: int, j: int) -> DataFrame:
        return self.rows.groupBy(F.col(f"`{self.links[i].column}`").alias("_a"), F.col(f"`{self.links[j].column}`").alias("_b")).agg(F.count("*").alias("_c"))

    def cooc_bounds(self, i: int, j: int) -> dict[str, int]:
        """Non-zeros of the count matrix of two links: bounds and a sketch estimate (exact: count of cooc)."""
        a, b = (f"`{self.links[k].column}`" for k in (i, j))
        r = self.rows.agg(F.count("*").alias("n"), F.count_distinct(F.col(a)).alias("a"), F.count_distinct(F.col(b)).alias("b"), F.approx_count_distinct(F.struct(a, b)).alias("e")).first()
        return {"low": max(r["a"], r["b"]), "high": r["n"], "estimate": r["e"]}

    def _cross_cells(self, i: int, j: int, pairs: str) -> tuple[DataFrame, int, int]:
        """Rows (p, v) of the product of two links' features, and which of them has the rows of it.

        One block is looked up and folded along the other link: the one with fewer targets, so that few groups
        are shuffled. A sparse block is folded rather than looked up.
        """
        if (isinstance(self.links[i].block, Coo), -self.links[i].block.rows_estimate()) > (isinstance(self.links[j].block, Coo), -self.links[j].block.rows_estimate()):
            i, j = j, i
        a, b = self.links[i], self.links[j]
        if pairs == "cooc":
            base, w = self.cooc(i, j), F.col("_c")
        else:
            base, w = self.rows.select(F.col(f"`{a.column}`").alias("_a"), F.col(f"`{b.column}`").alias("_b")), F.lit(1)
        wide = a.block.wide() if isinstance(a.block, Coo) else a.block
        cols = [f"_m{k}" for k in range(len(wide.names))]
        moved = _met(base, "_a", wide).groupBy("_b").agg(*[F.sum(w * F.col(f"`{c}`")).alias(m) for c, m in zip(wide.names, cols)])
        return b.block.fold_cells(moved, "_b", cols), j, i

    def _cross(self, i: int, j: int, pairs: str) -> np.ndarray:
        cells, a, b = self._cross_cells(i, j, pairs)
        shape = len(self.links[a].block.names), len(self.links[b].block.names)
        got = dense.gathered([(cells, shape[0] * shape[1])])[0].reshape(shape)
        return got if (a, b) == (i, j) else got.T

    def kernel(self, on: str = "_row", max_rows: int = 5000) -> DataFrame:
        """T T^T in long form (r, s, value) with r <= s, by the row id `on`; see Transposed.gram.

        Up to max_rows rows are numbered in the order of their ids, on the driver, and each target meets all
        rows once. More rows meet block by block (kernel_blocks), and no id comes to the driver.
        """
        from foldstar.double import outer

        if self.n_rows() > max_rows:
            return self._kernel_by_blocks(on)
        ids = [r[0] for r in self.rows.select(on).orderBy(on).collect()]
        if len(set(ids)) < len(ids):
            raise ValueError(f"`{on}` does not tell the rows apart")
        spark = self.rows.sparkSession
        kind = self.rows.schema[on].dataType.simpleString()
        known = spark.createDataFrame([(v, i) for i, v in enumerate(ids)], f"_id {kind}, _n long")
        here = self.on(self.rows.join(F.broadcast(known), F.col(f"`{on}`") == F.col("_id")).drop("_id", "_row").withColumnRenamed("_n", "_row"))
        cells = outer(here, here, max_rows).where("r <= s")
        name = lambda c: known.select(F.col("_n").alias(c), F.col("_id").alias(f"_{c}"))
        return cells.join(F.broadcast(name("r")), "r").join(F.broadcast(name("s")), "s").select(F.col("_r").alias("r"), F.col("_s").alias("s"), "value")

    def _kernel_by_blocks(self, on: str) -> DataFrame:
        if not self.rows.groupBy(F.col(f"`{on}`")).count().where("count > 1").isEmpty():
            raise ValueError(f"`{on}` does not tell the rows apart")
        kind = self.rows.schema[on].dataType.simpleString()

        def cells(a, b, g):
            import pandas as pd

            i, j = np.triu_indices(len(a)) if a is b else (x.ravel() for x in np.indices(g.shape))
            r, s = a[i], b[j]
            return pd.DataFrame({"r": np.where(r <= s, r, s), "s": np.where(r <= s, s, r), "value": g[i, j]})

        return self.kernel_blocks(on, cells, f"r {kind}, s {kind}, value double", 1000, half=True)

    def plus(self, other: FactoredMatrix) -> FactoredMatrix:
        """T1 + T2 over one row frame with the same links: own features and blocks add up by key, so the sum is factored too.

        Blocks must hold the same keys (`total`); features take the names of T1. Other sums are not factored.
        """
        if [k.column for k in self.links] != [k.column for k in other.links] or [len(k.block.names) for k in self.links] != [len(k.block.names) for k in other.links] or len(self.own) != len(other.own):
            raise ValueError("both matrices must have the same links and widths; materialize them otherwise")
        if any(isinstance(k.block, Coo) for k in [*self.links, *other.links]):
            raise ValueError("sparse blocks: convert them first (Coo.wide)")
        rows = self.rows
        if self.own:
            ids = [c for c in self.rows.columns if c not in self.own and c in other.rows.columns]
            theirs = other.rows.select(*[F.col(f"`{c}`").alias(f"_j{i}") for i, c in enumerate(ids)], *[F.col(f"`{c}`").alias(f"_a{i}") for i, c in enumerate(other.own)])
            met = rows.join(theirs, [F.col(f"`{c}`").eqNullSafe(F.col(f"_j{i}")) for i, c in enumerate(ids)])
            keep = [F.col(f"`{c}`") for c in rows.columns if c not in self.own]
            rows = met.select(*keep, *[(F.col(f"`{c}`") + F.col(f"_a{i}")).alias(c) for i, c in enumerate(self.own)])
        links = []
        for k, q in zip(self.links, other.links):
            theirs = q.block.df.select(F.col(f"`{q.block.key}`").alias("_k"), *[F.col(f"`{c}`").alias(f"_a{i}") for i, c in enumerate(q.block.names)])
            both = k.block.df.join(theirs, F.col(f"`{k.block.key}`") == F.col("_k"))
            links.append(Link(k.column, Wide(both.select(F.col(f"`{k.block.key}`"), *[(F.col(f"`{c}`") + F.col(f"_a{i}")).alias(c) for i, c in enumerate(k.block.names)]), k.block.key, k.block.names)))
        return FactoredMatrix(rows, self.own, links, [*self.trace, "sum of blocks"])

    def kernel_blocks(self, on: str, of, schema: str, block: int = 2000, half: bool = False) -> DataFrame:
        """Every block of T T^T, of `block` rows by `block` rows about: the frames of of(ids, ids, values).

        For any number of rows: a block is bounded and never stored, and what stays is what `of` returns. The
        work is the square of the rows all the same. `on` is a row id (long). half: of two blocks' rows one order
        comes only, and ids keep their type; a block with itself comes as of(ids, the same object, values).
        """
        key = F.col(f"`{on}`") if half else F.col(f"`{on}`").cast("long")
        t = self.materialize().frame.select(key.alias("id"), F.array(*[F.col(f"`{c}`").cast("double") for c in self.names]).alias("x"))
        n = max(1, -(-self.n_rows() // block))
        packed = t.groupBy(F.pmod(F.xxhash64("id"), F.lit(n)).alias("p")).agg(F.collect_list(F.struct("id", "x")).alias("rows"))
        side = lambda s: packed.select(F.col("p").alias(f"p{s}"), F.col("rows")["id"].alias(f"id{s}"), F.flatten(F.col("rows")["x"]).alias(f"x{s}"))

        def run(frames):
            for f in frames:
                for p, a, x, q, b, y in zip(f["pa"], f["ida"], f["xa"], f["pb"], f["idb"], f["xb"]):
                    a, b = np.asarray(a), np.asarray(b)
                    g = np.asarray(x).reshape(len(a), -1) @ np.asarray(y).reshape(len(b), -1).T
                    yield of(a, a if half and p == q else b, g)

        met = side("a").crossJoin(side("b"))
        return (met.where("pa <= pb") if half else met).select("pa", "ida", "xa", "pb", "idb", "xb").mapInPandas(run, schema)

    def kernel_extremes(self, on: str, names: tuple[str, str], most: int = 8_000_000) -> DataFrame:
        """Columns `on`, n, smallest, largest: for each row of T its products with all n rows, without the square of the rows.

        A product is linear in the other row, so its extremes are at corners of the convex hull of all rows. Rows
        that agree but in the two columns `names` form a class, and only the corners of its hull in these two
        are met. Parts are joined with their class and the two columns alone. Beyond `most` cells of corners, or
        with values that are not finite, all blocks of rows meet.
        """
        from foldstar.extremes import classes, corners, label, met

        parts, rows = [], None
        sides = [(self.rows, self.own, [F.col(f"`{on}`").alias("id"), *[F.col(f"`{k.column}`").alias(f"_f{i}") for i, k in enumerate(self.links, 1)]])]
        for i, k in enumerate(self.links, 1):
            block = k.block.wide() if isinstance(k.block, Coo) else k.block
            sides.append((block.df, block.names, [F.col(f"`{block.key}`").alias(f"_k{i}")]))
        for i, (frame, have, ids) in enumerate(sides):
            rest = [c for c in have if c not in names]
            if (part := classes(frame, rest, most // self.d)) is None:
                break
            parts.append(part)
            narrow = frame.select(*ids, label(rest).alias(f"h{i}"), *[F.col(f"`{c}`").cast("double").alias(a) for c, a in zip(names, "uv") if c in have])
            rows = narrow if rows is None else rows.join(narrow, F.col(f"_f{i}") == F.col(f"_k{i}")).drop(f"_f{i}", f"_k{i}")
        found = None
        if len(parts) == len(sides) and np.prod([float(len(h)) for h, _ in parts]) < 2**62:
            rows = cut(rows.select("id", *[f"h{i}" for i in range(len(sides))], "u", "v"), "narrow-rows")
            found = corners(rows, [h for h, _ in parts], self.d, most)
        kind = self.rows.schema[on].dataType.simpleString()
        if found is None:
            def ends(a, b, g):
                import pandas as pd

                return pd.DataFrame({on: a, "n": len(b), "smallest": g.min(axis=1), "largest": g.max(axis=1)})

            return self.kernel_blocks(on, ends, f"`{on}` long, n long, smallest double, largest double")
        return met(rows, parts, found, on, kind)

    def elementwise(self, x: DataFrame, on: str, op) -> DataFrame:
        """T op X for a regular matrix keyed by a row id: nothing to factor, so the joined table is used."""
        t = self.materialize().frame
        both = t.alias("t").join(x.alias("x"), on)
        return both.select(on, *[op(F.col(f"t.`{c}`"), F.col(f"x.`{c}`")).alias(c) for c in self.names])

    def create_view(self, name: str) -> None:
        """Parts as temporary views, and the logical T as a view over their join."""
        self.rows.createOrReplaceTempView(f"{name}_rows")
        for i, k in enumerate(self.links):
            k.block.df.createOrReplaceTempView(f"{name}_block{i}")
        self.materialize().frame.createOrReplaceTempView(name)

    def explain(self) -> str:
        return " > ".join(t for t in self.trace if t)
