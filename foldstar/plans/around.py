"""Registered queries of the sources, functions and relational operators around the methods."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from foldstar.lineage import cut
from foldstar.operators import links
from foldstar.plans.queries import sql_pairs, upper
from foldstar.sources import tables
from foldstar.workloads import FIXTURES, LINE4, block, read

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str):
    def register(fn):
        QUERIES[fn.__name__], ORACLES[fn.__name__] = fn, sql
        return fn

    return register


K = FIXTURES["k1min"]
NAMES = list(K.features)
CELLS = [(a, b) for i, a in enumerate(NAMES) for b in NAMES[i:]]
GRAM = sql_pairs(K, CELLS, lambda a, b: f"coalesce(sum({a} * {b}), 0)")


@query("SELECT l_orderkey, l_quantity, l_extendedprice * (1 - l_discount) AS revenue FROM lineitem WHERE l_shipdate < DATE '1996-01-01' AND l_returnflag IN ('A', 'R') AND l_quantity BETWEEN 10 AND 20 AND l_linestatus LIKE 'F%'")
def scan_filter_project(s, d):
    where = (F.col("l_shipdate") < F.lit("1996-01-01").cast("timestamp_ntz")) & F.col("l_returnflag").isin("A", "R") & F.col("l_quantity").between(10, 20) & F.col("l_linestatus").like("F%")
    return tables.scan(s, d, "lineitem", where=where).select("l_orderkey", "l_quantity", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"))


@query(GRAM.replace("FROM lineitem JOIN", "FROM (SELECT * FROM lineitem WHERE l_quantity > 20) JOIN"))
def filter_entity_gram(s, d):
    return upper(s, NAMES, K.build(s, d).filter_rows("l_qty > 20").gram())


@query(GRAM.replace("JOIN part ON", "JOIN (SELECT * FROM part WHERE p_size <= 10) ON"))
def filter_attr_gram(s, d):
    return upper(s, NAMES, K.build(s, d).filter_block(0, "p_sz <= 10").gram())


@query(GRAM.replace("FROM lineitem JOIN", "FROM (SELECT * FROM lineitem WHERE l_linenumber < 3 UNION ALL SELECT * FROM lineitem WHERE l_linenumber > 5) JOIN"))
def vstack_gram(s, d):
    t = K.build(s, d)
    return upper(s, NAMES, t.filter_rows("l_linenumber < 3").vstack(t.filter_rows("l_linenumber > 5")).gram())


@query(GRAM)
def sql_view_gram(s, d):
    K.build(s, d).create_view("k1min_t")
    cells = ", ".join(f"sum({a} * {b})" for a, b in CELLS)
    names = ", ".join(f"'{a}|{b}'" for a, b in CELLS)
    made = s.sql(f"SELECT inline(arrays_zip(array({names}), array({cells}))) FROM k1min_t").toDF("n", "value")
    return made.select(F.split("n", "[|]")[0].alias("i"), F.split("n", "[|]")[1].alias("j"), "value")


@query("SELECT unnest(['broadcast', 'merge', 'shuffle_hash']) AS strategy, (SELECT count(*) FROM lineitem JOIN part ON l_partkey = p_partkey) AS n, (SELECT sum(l_quantity * p_size) FROM lineitem JOIN part ON l_partkey = p_partkey) AS total")
def join_inner_strategies(s, d):
    li, p = read(s, d, "lineitem").select("l_partkey", "l_quantity"), read(s, d, "part").select("p_partkey", "p_size")
    out = None
    for h in ("broadcast", "merge", "shuffle_hash"):
        one = li.join(p.hint(h), F.col("l_partkey") == F.col("p_partkey")).agg(F.lit(h).alias("strategy"), F.count("*").alias("n"), F.sum(F.col("l_quantity") * F.col("p_size")).alias("total"))
        out = one if out is None else out.unionByName(one)
    return out.select("strategy", "n", "total")


@query("SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def semi_trim_orders(s, d):
    return links.referenced(read(s, d, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", read(s, d, "lineitem").select("l_orderkey"), "l_orderkey")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def anti_unreferenced(s, d):
    return links.dangling(read(s, d, "orders").select("o_orderkey"), "o_orderkey", read(s, d, "lineitem").select("l_orderkey"), "l_orderkey")


@query("SELECT count(*) AS n, count(c_custkey) AS with_customer, count(o_orderkey) AS with_order FROM customer FULL JOIN orders ON c_custkey = o_custkey")
def outer_audit(s, d):
    c, o = read(s, d, "customer").select("c_custkey"), read(s, d, "orders").select("o_custkey", "o_orderkey")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "full").agg(F.count("*").alias("n"), F.count("c_custkey").alias("with_customer"), F.count("o_orderkey").alias("with_order"))


@query("SELECT count(*) AS n, sum(s_suppkey + r_regionkey)::BIGINT AS total FROM supplier, region")
def cartesian_sum(s, d):
    # the region table has a handful of rows by definition; its size is what makes this product legal
    a, b = read(s, d, "supplier").select("s_suppkey"), read(s, d, "region").select("r_regionkey")
    return a.crossJoin(b).agg(F.count("*").alias("n"), F.sum(F.col("s_suppkey") + F.col("r_regionkey")).alias("total"))


@query("SELECT o_orderkey, CAST(floor(o_totalprice / 50000) AS BIGINT) AS band FROM orders")
def range_join_orders(s, d):
    bands = s.range(0, 11).select(F.col("id").alias("band"), (F.col("id") * 50000.0).alias("low"), ((F.col("id") + 1) * 50000.0).alias("high"))
    return links.range_link(read(s, d, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", bands, "low", "high", "band", 50000.0).select("o_orderkey", "band")


@query("SELECT e.event_id, (SELECT max_by(o_orderkey, (o_orderdate, o_orderkey)) FROM orders o WHERE o.o_custkey = e.user_id AND o.o_orderdate <= e.ts) AS o_orderkey FROM events e")
def asof_event_order(s, d):
    e, o = read(s, d, "events").select("event_id", "user_id", "ts"), read(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return links.asof_link(e, "user_id", "ts", o, "o_custkey", "o_orderdate", "o_orderkey").select("event_id", "o_orderkey")


@query("SELECT sum(value_r * value_r) AS vv, sum(value_r * bal) AS vb, sum(bal * bal) AS bb, sum(value_r * reg) AS vr FROM (SELECT CAST(round(value) AS DOUBLE) AS value_r, CAST(round(c_acctbal) AS DOUBLE) AS bal, CAST(n_regionkey AS DOUBLE) AS reg FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey)")
def snowflake_gram(s, d):
    from foldstar.normalized import FactoredMatrix

    n = read(s, d, "nation").select("n_nationkey", "n_regionkey")
    c = read(s, d, "customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.round("c_acctbal").alias("bal"), F.col("n_regionkey").alias("reg"))
    t = FactoredMatrix.star(read(s, d, "events").select("user_id", F.round("value").alias("v")), [(c, "user_id", "c_custkey", ["bal", "reg"])], ["v"], total=True)
    g = t.gram()
    return s.createDataFrame([(float(g[0, 0]), float(g[0, 1]), float(g[1, 1]), float(g[0, 2]))], "vv double, vb double, bb double, vr double")


@query("SELECT l_returnflag, count(*) AS n, sum(l_quantity) AS total, avg(l_quantity) AS mean, min(l_quantity) AS low, max(l_quantity) AS high, round(var_samp(l_quantity), 6) AS variance, round(covar_samp(l_quantity, l_linenumber), 6) AS covariance, round(corr(l_quantity, l_linenumber), 6) AS correlation FROM lineitem GROUP BY 1")
def agg_basic(s, d):
    q, n = F.col("l_quantity"), F.col("l_linenumber")
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum(q).alias("total"), F.avg(q).alias("mean"), F.min(q).alias("low"), F.max(q).alias("high"), F.round(F.var_samp(q), 6).alias("variance"), F.round(F.covar_samp(q, n), 6).alias("covariance"), F.round(F.corr(q, n), 6).alias("correlation"))


@query("SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def distinct_counts(s, d):
    return read(s, d, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


for _mode, _sql in (("gsets", "GROUPING SETS ((l_suppkey), (l_linenumber))"), ("cube", "CUBE (l_suppkey, l_linenumber)"), ("rollup", "ROLLUP (l_suppkey, l_linenumber)")):

    def _fold(s, d, mode=_mode):
        return links.fold_all(read(s, d, "lineitem"), ["l_suppkey", "l_linenumber"], ["l_quantity"], mode)

    _name = {"gsets": "grouping_sets_fold", "cube": "cube_fold", "rollup": "rollup_fold"}[_mode]
    QUERIES[_name] = _fold
    ORACLES[_name] = f"SELECT l_suppkey, l_linenumber, grouping(l_suppkey, l_linenumber)::BIGINT AS level, count(*) AS hits, sum(l_quantity) AS l_quantity FROM lineitem GROUP BY {_sql}"


@query("SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS {t}" for t in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY 1")
def onehot_pivot(s, d):
    kinds = ["click", "error", "purchase", "signup", "view"]
    return read(s, d, "events").groupBy("user_id").pivot("event_type", kinds).count().na.fill(0)


@query("SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS orders, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS top FROM orders GROUP BY 1")
def pack_rows(s, d):
    o = read(s, d, "orders")
    return o.groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")), ",").alias("orders"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"))


@query("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER w AS bin FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def window_bins(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return read(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("bin"))


@query("SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first, sum(round(value)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS running FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def lag_features(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(s, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("value").over(w).alias("first"), F.sum(F.round("value")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"))


@query("SELECT event_id, sum(round(value)) OVER (PARTITION BY user_id ORDER BY CAST(epoch_us(ts) AS BIGINT) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS rolling FROM events")
def rolling_value(s, d):
    e = read(s, d, "events").withColumn("u", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("u").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.sum(F.round("value")).over(w).alias("rolling"))


@query("WITH t AS (" + K.sql() + ") SELECT * FROM (SELECT unnest([" + ", ".join(f"'{n}'" for n in NAMES) + "]) AS feature, unnest([" + ", ".join(f"sum({n})" for n in NAMES) + "]) AS value FROM t) ORDER BY value DESC LIMIT 3")
def topk_weights(s, d):
    from foldstar.plans.queries import vector

    return vector(s, NAMES, K.build(s, d).col_sums()).orderBy(F.desc("value")).limit(3)


@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def topk_per_group(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return read(s, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey")


@query("SELECT (SELECT count(*) FROM (SELECT user_id FROM events INTERSECT SELECT o_custkey FROM orders)) AS both, (SELECT count(*) FROM (SELECT user_id FROM events EXCEPT SELECT o_custkey FROM orders)) AS events_only, (SELECT count(*) FROM (SELECT user_id FROM events UNION SELECT o_custkey FROM orders)) AS either, (SELECT count(*) FROM (SELECT o_custkey FROM orders INTERSECT ALL SELECT user_id FROM events)) AS both_bag")
def set_overlap(s, d):
    e, o = read(s, d, "events").select("user_id"), read(s, d, "orders").select("o_custkey")
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(e.intersect(o), "both").crossJoin(n(e.subtract(o), "events_only")).crossJoin(n(e.union(o).distinct(), "either")).crossJoin(n(o.intersectAll(e), "both_bag"))


@query("SELECT doc_id, b::BIGINT AS bucket, count(*) AS n FROM (SELECT doc_id, CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) % 4096 AS b FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> '') GROUP BY 1, 2")
def hash_tokens(s, d):
    w = read(s, d, "documents").select("doc_id", F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    return w.groupBy("doc_id", (F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long") % 4096).alias("bucket")).agg(F.count("*").alias("n"))


@query("SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, count(*) AS pages, sum(length(html))::BIGINT AS chars FROM pages GROUP BY 1")
def host_profile(s, d):
    return read(s, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host")).agg(F.count("*").alias("pages"), F.sum(F.length("html")).alias("chars"))


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, dayofweek(o_orderdate)::INT + 1 AS dow, strftime(date_trunc('quarter', o_orderdate), '%Y-%m-%d') AS quarter, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days FROM orders")
def date_features(s, d):
    t = F.col("o_orderdate")
    return read(s, d, "orders").select("o_orderkey", F.year(t).alias("y"), F.month(t).alias("m"), F.dayofweek(t).alias("dow"), F.date_format(F.date_trunc("quarter", t), "yyyy-MM-dd").alias("quarter"), F.datediff(t, F.lit("1992-01-01").cast("date")).alias("days"))


@query("SELECT event_id, CAST(regexp_extract(props, '\"k\": ([0-9]+)', 1) AS BIGINT) AS k FROM events")
def json_feature(s, d):
    return read(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS norm2 FROM embeddings")
def array_dot(s, d):
    v = F.transform("embedding", lambda x: x.cast("double"))
    return read(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(v, v, lambda a, b: a * b), F.lit(0.0), lambda t, x: t + x), 6).alias("norm2"))


@query("SELECT vec_id, i::INT AS i, embedding[i + 1]::DOUBLE AS v FROM embeddings, (SELECT unnest(range(64)) AS i)")
def array_unpack(s, d):
    return read(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v")).select("vec_id", "i", F.col("v").cast("double").alias("v"))


@query("SELECT s_suppkey, CASE WHEN s_acctbal < 0 THEN 'debt' WHEN s_acctbal < 1000 THEN 'low' ELSE 'high' END AS band, coalesce(nullif(s_nationkey, 0), -1) AS nation, TRY_CAST(right(s_name, 3) AS INT) AS number FROM supplier")
def conditional_cast(s, d):
    b = F.col("s_acctbal")
    return read(s, d, "supplier").select("s_suppkey", F.when(b < 0, "debt").when(b < 1000, "low").otherwise("high").alias("band"), F.coalesce(F.nullif("s_nationkey", F.lit(0)), F.lit(-1)).alias("nation"), F.substring("s_name", -3, 3).try_cast("int").alias("number"))


@query("SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 5 = 2")
def hash_split(s, d):
    return tables.hash_split(read(s, d, "orders").select("o_orderkey"), "o_orderkey", 5, 2)


def _cofactor(s, d, window):
    """Co-factors of event value and customer balance per window, from the parts: the batch twin of the stream."""
    from foldstar.streaming.cofactor import cofactors

    return cofactors(read(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")), read(s, d, "customer"), window)


_COF = "SELECT strftime(w, '%Y-%m-%d %H:%M') AS start, count(*) AS n, sum(v) AS v, sum(b) AS b, sum(v * v) AS vv, sum(v * b) AS vb, sum(b * b) AS bb FROM ({}) GROUP BY w"
_EV = "SELECT {} AS w, round(value) AS v, round(c_acctbal) AS b FROM events JOIN customer ON user_id = c_custkey"


@query(_COF.format(_EV.format("time_bucket(INTERVAL 1 DAY, ts)")))
def tumbling_cofactor(s, d):
    return _cofactor(s, d, ("1 day", None))


@query(_COF.format("SELECT time_bucket(INTERVAL 6 HOUR, ts) - to_hours(6 * k) AS w, round(value) AS v, round(c_acctbal) AS b FROM events JOIN customer ON user_id = c_custkey, (SELECT unnest([0, 1, 2, 3]) AS k)"))
def sliding_cofactor(s, d):
    return _cofactor(s, d, ("1 day", "6 hours"))


@query("WITH e AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS grp FROM e) SELECT user_id, count(*) AS n, sum(round(value)) AS v, sum(round(value) * round(value)) AS vv FROM g GROUP BY user_id, grp")
def session_cofactor(s, d):
    e = read(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    v = F.round("value")
    return e.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"), F.sum(v).alias("v"), F.sum(v * v).alias("vv")).drop("session_window")


def _sparse(s, d):
    """labels joined with documents as a sparse block (words hashed, language and source one-hot)."""
    from foldstar.normalized import FactoredMatrix
    from foldstar.schema import FeatureSpec

    docs = read(s, d, "documents").select("doc_id", "lang", "source")
    coo = FeatureSpec(onehot={"lang": ["de", "en", "es", "fr"], "source": [f"src{i}" for i in range(20)]}).coo(docs, "doc_id")
    labels = read(s, d, "labels").select("doc_id", F.col("quality").cast("double").alias("quality"), F.col("toxic").cast("double").alias("toxic"))
    return FactoredMatrix.star(labels, [(coo, "doc_id", "doc_id", [])], ["quality", "toxic"], total=True)


_HOT = {f"lang_{i}": f"(lang = '{v}')::INT" for i, v in enumerate(["de", "en", "es", "fr"])} | {f"source_{i}": f"(source = 'src{i}')::INT" for i in range(20)}
_ALL = {"quality": "quality", "toxic": "toxic"} | _HOT
_SP = list(_ALL)


@query("WITH t AS (SELECT " + ", ".join(f"{e} AS {n}" for n, e in _ALL.items()) + " FROM labels JOIN documents USING (doc_id)) SELECT unnest([" + ", ".join(f"'{a}'" for i, a in enumerate(_SP) for _ in _SP[i:]) + "]) AS i, unnest([" + ", ".join(f"'{b}'" for i, _ in enumerate(_SP) for b in _SP[i:]) + "]) AS j, unnest([" + ", ".join(f"sum({a} * {b})::DOUBLE" for i, a in enumerate(_SP) for b in _SP[i:]) + "]) AS value FROM t")
def gram_sparse_documents(s, d):
    t = _sparse(s, d)
    return upper(s, t.names, t.gram())


def gram_sparse_text_documents(s, d):
    """The long Gram of labels (0: quality, 1: toxic) and documents (2 to 25: language, source; then 2**12 hashed words)."""
    from foldstar.schema import FeatureSpec

    labelled = read(s, d, "labels").select("doc_id").distinct()
    docs = read(s, d, "documents").select("doc_id", "lang", "source", "text").join(labelled, "doc_id", "left_semi")  # no other document has a hit
    coo = FeatureSpec(onehot={"lang": ["de", "en", "es", "fr"], "source": [f"src{i}" for i in range(20)]}, hashed=["text"]).coo(docs, "doc_id")
    coo.df = cut(coo.df, "cells")
    labels = read(s, d, "labels").join(docs.select("doc_id"), "doc_id", "left_semi")
    own = [F.col(n).cast("double").alias(n) for n in ("quality", "toxic")]
    sums = labels.select("doc_id", *own).groupBy("doc_id").agg(F.count("*").alias("_hits"), *[F.sum(n).alias(n) for n in ("quality", "toxic")])
    inner = coo.gram_long(sums.select("doc_id", "_hits"), "doc_id").select((F.col("i") + 2).alias("i"), (F.col("j") + 2).alias("j"), "value")
    cell = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(n).alias("u")) for i, n in enumerate(("quality", "toxic"))])).alias("c")
    met = sums.select("doc_id", cell).select("doc_id", "c.*").where("u <> 0").join(coo.df, "doc_id")
    mixed = met.groupBy("i", (F.col("col") + 2).alias("j")).agg(F.sum(F.col("u") * F.col("val")).alias("value"))
    q, t = F.col("quality").cast("double"), F.col("toxic").cast("double")
    squares = labels.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), v.alias("v")) for i, j, v in ((0, 0, q * q), (0, 1, q * t), (1, 1, t * t))])).alias("c")).select("c.*").where("v <> 0")
    return inner.unionByName(mixed).unionByName(squares.groupBy("i", "j").agg(F.sum("v").alias("value"))).select(F.col("i").cast("int").alias("i"), F.col("j").cast("int").alias("j"), "value")


#: Without SQL, which is too slow for all pairs of 2**12 columns: brute force on a small fixture instead.
LONG = {"gram_sparse_text_documents": gram_sparse_text_documents}


@query("SELECT conv_id, count(*) AS turns, avg(length(text)) AS mean_chars, avg((role = 'user')::INT) AS user_share FROM conversations GROUP BY 1")
def conversation_profile(s, d):
    return read(s, d, "conversations").groupBy("conv_id").agg(F.count("*").alias("turns"), F.avg(F.length("text")).alias("mean_chars"), F.avg((F.col("role") == "user").cast("int")).alias("user_share"))
