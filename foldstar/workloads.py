"""The experiment workloads on the given tables: feature sets, factored fixtures, and the same T in SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from foldstar.keyed import KeyedJoin
from foldstar.normalized import Coo, FactoredMatrix, KeyNames, Wide

# The domains of the nominal columns.
BRANDS = [f"Brand#{i}" for i in range(1, 26)]
TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
STATUSES = ["F", "O", "P"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _num(sql: str) -> str:
    return f"CAST({sql} AS DOUBLE)"


def _hot(column: str, values: list, prefix: str) -> dict[str, str]:
    lit = lambda v: f"'{v}'" if isinstance(v, str) else str(v)
    return {f"{prefix}{i:02d}": f"CAST(CASE WHEN {column} = {lit(v)} THEN 1 ELSE 0 END AS DOUBLE)" for i, v in enumerate(values)}


# Feature sets: name to SQL text that both engines read. Whole numbers, so that sums are exact.
LINE4 = {"l_qty": _num("l_quantity"), "l_price": _num("round(l_extendedprice)"), "l_disc": _num("round(l_discount * 100)"), "l_taxp": _num("round(l_tax * 100)")}
LINE9 = LINE4 | _hot("l_returnflag", ["A", "N", "R"], "l_rf") | _hot("l_linestatus", ["F", "O"], "l_ls")
PART2 = {"p_sz": _num("p_size"), "p_retail": _num("round(p_retailprice)")}
PART33 = _hot("p_brand", BRANDS, "p_br") | _hot("p_type", TYPES, "p_ty") | PART2
SUPP31 = _hot("s_nationkey", list(range(25)), "s_na") | _hot("n_regionkey", list(range(5)), "s_re") | {"s_bal": _num("round(s_acctbal)")}
NAT30 = _hot("n_nationkey", list(range(25)), "n_na") | _hot("n_regionkey", list(range(5)), "n_re")
ORD9 = _hot("o_orderpriority", PRIORITIES, "o_pr") | _hot("o_orderstatus", STATUSES, "o_st") | {"o_total": _num("round(o_totalprice / 100)")}
CUST36 = _hot("c_nationkey", list(range(25)), "c_na") | _hot("n_regionkey", list(range(5)), "c_re") | _hot("c_mktsegment", SEGMENTS, "c_sg") | {"c_bal": _num("round(c_acctbal)")}
EV7 = {"e_value": _num("round(value)")} | _hot("event_type", EVENT_TYPES, "e_ty") | {"e_k": _num("CAST(regexp_extract(props, '([0-9]+)', 1) AS INT)")}


def emb(width: int = 64, duck: bool = False) -> dict[str, str]:
    return {f"v_{i:02d}": _num(f"round(CAST(embedding[{i + duck}] AS DOUBLE) * 1000)") for i in range(width)}


def _wide(df: DataFrame, key: str, features: dict[str, str]) -> Wide:
    return Wide(df.select(key, *[F.expr(e).alias(n) for n, e in features.items()]), key, list(features))


def _with_nation(spark, sf, name, key) -> DataFrame:
    n = read(spark, sf, "nation").select("n_nationkey", "n_regionkey")
    return read(spark, sf, name).join(n, F.col(key) == F.col("n_nationkey"))


def block(spark: SparkSession, sf: str, name: str) -> Wide:
    if name == "part33":
        return _wide(read(spark, sf, "part"), "p_partkey", PART33)
    if name == "part2":
        return _wide(read(spark, sf, "part"), "p_partkey", PART2)
    if name == "supp31":
        return _wide(_with_nation(spark, sf, "supplier", "s_nationkey"), "s_suppkey", SUPP31)
    if name == "ord9":
        return _wide(read(spark, sf, "orders"), "o_orderkey", ORD9)
    if name == "cust36":
        return _wide(_with_nation(spark, sf, "customer", "c_nationkey"), "c_custkey", CUST36)
    if name == "nat30":
        return _wide(read(spark, sf, "nation"), "n_nationkey", NAT30)
    if name == "ev7":
        return _wide(read(spark, sf, "events"), "event_id", EV7)
    if name == "emb64":
        return _wide(read(spark, sf, "embeddings"), "vec_id", emb())
    raise KeyError(name)


LINE_IDS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


def _star(entity: str, own: dict[str, str], ids: list[str], links: list[tuple[str, str]], extra: dict[str, str] | None = None) -> Callable:
    def build(spark, sf):
        df = read(spark, sf, entity)
        keep = list(dict.fromkeys([*ids, *[fk for _, fk in links]]))
        rows = df.select(*keep, *[F.expr(e).alias(n) for n, e in (own | (extra or {})).items()])
        blocks = [block(spark, sf, b) for b, _ in links]
        return FactoredMatrix.star(rows, [(b, fk, b.key, b.names) for b, (_, fk) in zip(blocks, links)], list(own), [*ids, *(extra or {})], total=True)

    return build


def _mn(spark, sf):
    c, s = read(spark, sf, "customer"), read(spark, sf, "supplier")
    return FactoredMatrix.mn(block(spark, sf, "cust36"), block(spark, sf, "supp31"), c.select("c_custkey", F.col("c_nationkey").alias("j")), s.select("s_suppkey", F.col("s_nationkey").alias("j")))


def _eo(spark, sf):
    e, o = read(spark, sf, "events"), read(spark, sf, "orders")
    return FactoredMatrix.mn(block(spark, sf, "ev7"), block(spark, sf, "ord9"), e.select("event_id", F.col("user_id").alias("j")), o.select("o_orderkey", F.col("o_custkey").alias("j")))


def _ch(spark, sf):
    blocks = [block(spark, sf, b) for b in ("supp31", "cust36", "ev7")]
    tables = [read(spark, sf, t) for t in ("supplier", "customer", "events")]
    return FactoredMatrix.chain(blocks, tables, [("s_nationkey", "c_nationkey"), ("c_custkey", "user_id")])


def keyed(spark: SparkSession, sf: str, name: str) -> KeyedJoin:
    def t(table, features, *extra):
        df = _with_nation(spark, sf, table, extra[0]) if table in ("supplier", "customer") else read(spark, sf, table)
        return df.select(*dict.fromkeys(extra), *[F.expr(e).alias(n) for n, e in features.items()]), list(features)

    if name == "mn":
        return KeyedJoin([t("customer", CUST36, "c_nationkey"), t("supplier", SUPP31, "s_nationkey")], [("c_nationkey", "s_nationkey")])
    if name == "eo":
        return KeyedJoin([t("events", EV7, "user_id"), t("orders", ORD9, "o_custkey")], [("user_id", "o_custkey")])
    return KeyedJoin([t("supplier", SUPP31, "s_nationkey"), t("customer", CUST36, "c_nationkey", "c_custkey"), t("events", EV7, "user_id")], [("s_nationkey", "c_nationkey"), ("c_custkey", "user_id")])


@dataclass(frozen=True)
class Fixture:
    build: Callable[[SparkSession, str], FactoredMatrix]
    ids: dict[str, str]  # result column to column of the row frame
    features: dict[str, str]  # in T's order, as DuckDB SQL
    tables: str  # FROM clause of the joined form
    columns: tuple[str, ...] = ()

    def sql(self, extra: str = "") -> str:
        cols = ", ".join(f"{e} AS {n}" for n, e in self.features.items())
        return f"SELECT {', '.join(self.ids)}{extra}, {cols} FROM {self.tables}"


_SUPP = "(SELECT s.*, n_regionkey FROM supplier s JOIN nation ON s_nationkey = n_nationkey)"
_CUST = "(SELECT c.*, n_regionkey FROM customer c JOIN nation ON c_nationkey = n_nationkey)"
_CR = {n: e.replace("n_regionkey", "cr.n_regionkey") for n, e in CUST36.items()}
_SR = {n: e.replace("n_regionkey", "sr.n_regionkey") for n, e in SUPP31.items()}
_LID = {c: c for c in LINE_IDS}

FIXTURES: dict[str, Fixture] = {
    "k1": Fixture(_star("lineitem", LINE4, LINE_IDS, [("part33", "l_partkey")]), _LID, LINE4 | PART33, "lineitem JOIN part ON l_partkey = p_partkey"),
    "k1min": Fixture(_star("lineitem", LINE4, LINE_IDS, [("part2", "l_partkey")]), _LID, LINE4 | PART2, "lineitem JOIN part ON l_partkey = p_partkey"),
    "k1o": Fixture(_star("lineitem", LINE4, LINE_IDS, [("ord9", "l_orderkey")]), _LID, LINE4 | ORD9, "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "k2": Fixture(_star("lineitem", LINE9, LINE_IDS, [("part33", "l_partkey"), ("supp31", "l_suppkey")]), _LID, LINE9 | PART33 | SUPP31, f"lineitem JOIN part ON l_partkey = p_partkey JOIN {_SUPP} sr ON l_suppkey = s_suppkey"),
    "k2z": Fixture(_star("lineitem", {}, LINE_IDS, [("part33", "l_partkey"), ("supp31", "l_suppkey")]), _LID, PART33 | SUPP31, f"lineitem JOIN part ON l_partkey = p_partkey JOIN {_SUPP} sr ON l_suppkey = s_suppkey"),
    "k3": Fixture(_star("lineitem", LINE9, LINE_IDS, [("part33", "l_partkey"), ("supp31", "l_suppkey"), ("ord9", "l_orderkey")]), _LID, LINE9 | PART33 | SUPP31 | ORD9, f"lineitem JOIN part ON l_partkey = p_partkey JOIN {_SUPP} sr ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey"),
    "d1": Fixture(_star("events", EV7, ["event_id"], [("emb64", "user_id")]), {"event_id": "event_id"}, EV7 | emb(duck=True), "events JOIN embeddings ON user_id = vec_id"),
    "d2": Fixture(_star("events", EV7, ["event_id"], [("cust36", "user_id"), ("emb64", "user_id")]), {"event_id": "event_id"}, EV7 | _CR | emb(duck=True), f"events JOIN {_CUST} cr ON user_id = c_custkey JOIN embeddings ON user_id = vec_id"),
    "oc": Fixture(_star("orders", ORD9, ["o_orderkey"], [("cust36", "o_custkey")]), {"o_orderkey": "o_orderkey"}, ORD9 | _CR, f"orders JOIN {_CUST} cr ON o_custkey = c_custkey"),
    "sn": Fixture(_star("supplier", {"s_bal": SUPP31["s_bal"]}, ["s_suppkey"], [("nat30", "s_nationkey")]), {"s_suppkey": "s_suppkey"}, {"s_bal": SUPP31["s_bal"]} | NAT30, "supplier JOIN nation ON s_nationkey = n_nationkey"),
    "mn": Fixture(_mn, {"c_custkey": "_p0", "s_suppkey": "_p1"}, _CR | _SR, f"{_CUST} cr JOIN {_SUPP} sr ON c_nationkey = s_nationkey"),
    "eo": Fixture(_eo, {"event_id": "_p0", "o_orderkey": "_p1"}, EV7 | ORD9, "events JOIN orders ON user_id = o_custkey"),
    "ch": Fixture(_ch, {"s_suppkey": "_p0", "c_custkey": "_p1", "event_id": "_p2"}, _SR | _CR | EV7, f"{_SUPP} sr JOIN {_CUST} cr ON s_nationkey = c_nationkey JOIN events ON user_id = c_custkey"),
}

#: Features for gradient methods, scaled by constants; the targets are kept beside the rows.
SCALED = {"l_price": _num("l_extendedprice / 100000"), "l_disc": _num("l_discount * 10"), "l_taxp": _num("l_tax * 12.5")}
SCALED_PART = {"p_sz": _num("p_size / 50"), "p_retail": _num("p_retailprice / 1000")}
TARGETS = {"y": "CAST(CASE WHEN l_quantity > 25 THEN 1 ELSE -1 END AS DOUBLE)", "q": _num("l_quantity")}


def _g1(spark, sf):
    df = read(spark, sf, "lineitem").select(*LINE_IDS, *[F.expr(e).alias(n) for n, e in (SCALED | TARGETS).items()])
    return FactoredMatrix.star(df, [(_wide(read(spark, sf, "part"), "p_partkey", SCALED_PART), "l_partkey", "p_partkey", [])], list(SCALED), [*LINE_IDS, *TARGETS], total=True)


FIXTURES["g1"] = Fixture(_g1, _LID, SCALED | SCALED_PART, "lineitem JOIN part ON l_partkey = p_partkey")


#: Full feature sets for the learning methods, scaled by constants and not negative.
FULL = SCALED | _hot("l_returnflag", ["A", "N", "R"], "l_rf") | _hot("l_linestatus", ["F", "O"], "l_ls")
FULL_PART = _hot("p_brand", BRANDS, "p_br") | _hot("p_type", TYPES, "p_ty") | SCALED_PART
FULL_SUPP = _hot("s_nationkey", list(range(25)), "s_na") | _hot("n_regionkey", list(range(5)), "s_re") | {"s_bal": _num("(s_acctbal + 1000) / 11000")}
FULL_ORD = _hot("o_orderpriority", PRIORITIES, "o_pr") | _hot("o_orderstatus", STATUSES, "o_st") | {"o_total": _num("o_totalprice / 500000")}


def _full(own: dict[str, str], orders: bool = False) -> Callable:
    def build(spark, sf):
        df = read(spark, sf, "lineitem").select(*LINE_IDS, *[F.expr(e).alias(n) for n, e in (own | TARGETS).items()])
        blocks = [(_wide(read(spark, sf, "part"), "p_partkey", FULL_PART), "l_partkey"), (_wide(_with_nation(spark, sf, "supplier", "s_nationkey"), "s_suppkey", FULL_SUPP), "l_suppkey")]
        if orders:
            blocks.append((_wide(read(spark, sf, "orders"), "o_orderkey", FULL_ORD), "l_orderkey"))
        return FactoredMatrix.star(df, [(b, fk, b.key, b.names) for b, fk in blocks], list(own), [*LINE_IDS, *TARGETS], total=True)

    return build


_FROM2 = f"lineitem JOIN part ON l_partkey = p_partkey JOIN {_SUPP} sr ON l_suppkey = s_suppkey"
FIXTURES["f2"] = Fixture(_full(FULL), _LID, FULL | FULL_PART | FULL_SUPP, _FROM2)
FIXTURES["f2z"] = Fixture(_full({}), _LID, FULL_PART | FULL_SUPP, _FROM2)
FIXTURES["f3"] = Fixture(_full(FULL, True), _LID, FULL | FULL_PART | FULL_SUPP | FULL_ORD, _FROM2 + " JOIN orders ON l_orderkey = o_orderkey")


def _all_pairs(spark, sf):
    """Supplier with region on a constant: one join value, all pairs."""
    return FactoredMatrix.mn(block(spark, sf, "supp31"), _wide(read(spark, sf, "region"), "r_regionkey", REG2))


REG2 = {"r_key": _num("r_regionkey + 1"), "r_len": _num("length(r_name)")}
FIXTURES["xx"] = Fixture(_all_pairs, {"s_suppkey": "_p0", "r_regionkey": "_p1"}, _SR | REG2, f"{_SUPP} sr, region")


def with_keys(spark: SparkSession, sf: str) -> FactoredMatrix:
    """k2z with the keys themselves as identity columns: part33 and supp31 as sparse blocks, d grows with the tables."""
    from foldstar.schema import numbered

    blocks = []
    for name, fk in (("part33", "l_partkey"), ("supp31", "l_suppkey")):
        b = block(spark, sf, name)
        keys = numbered(b.df.select(b.key), b.key, len(b.names))
        cells = b.cells().select(F.col("_key").alias(b.key), "col", "val").unionByName(keys.select(b.key, "col", F.lit(1.0).alias("val")))
        blocks.append((Coo(cells, b.key, [*b.names, *KeyNames(b.key, keys.count())], b.df.select(b.key)), fk))
    return FactoredMatrix.star(read(spark, sf, "lineitem").select("l_partkey", "l_suppkey"), [(b, fk, b.key, []) for b, fk in blocks], [], total=True)


def thinned(spark: SparkSession, sf: str, m: int) -> FactoredMatrix:
    """k1 with about m of 30 line items kept: the tuple-ratio sweep."""
    t = FIXTURES["k1"].build(spark, sf)
    return t.filter_rows((7 * F.col("l_orderkey") + 11 * F.col("l_suppkey") + F.col("l_linenumber")) % 30 < m)


def self_join(spark: SparkSession, sf: str, n_u: int, width: int = 64) -> KeyedJoin:
    """embeddings with itself on vec_id mod n_u: the domain-size sweep."""
    e = read(spark, sf, "embeddings")
    f = emb(width)
    side = lambda p: (e.select((F.col("vec_id") % n_u).alias("j"), *[F.expr(x).alias(p + n) for n, x in f.items()]), [p + n for n in f])
    return KeyedJoin([side("a_"), side("b_")], [("j", "j")])
