"""Line dedup: a suffix array over line-ID sequences by distributed prefix doubling, and its common-prefix intervals.

Lines with a word get IDs in the order of their 128-bit digests; a suffix starts at every such line of
every document and ends with the document.

1. Doubling. Ranks by the first 1, 2, 4, ... lines: a rank is the number of suffixes that sort before.
   A step pairs the rank of a suffix with the rank of the suffix so many lines on, until every rank is
   unique or the suffixes that share it have come to their end (they are equal).
2. Longest common prefixes of neighbours in that order, from the ranks they shared on the way: the
   largest shared power of two, then the same again behind it.
3. Intervals. Neighbours whose common prefix has `min_lines` lines or more are one interval: its members
   start copies of one repeated run. The first copy, by (key, place), stays; the lines of later
   copies are deleted. Longer intervals lie inside these and start inside the same stretches.

`runs` lists the maximal repeated runs. A run of one line counts too if it has `single_words` words or more
(None: never); shorter lines go only inside longer runs, which protects headings, list marks and the like. Copies are found over all data.

Ranks are counted over distinct keys (aggregated map-side), so a line that a third of all rows hold
is one row there. Everything sorted is dealt by ranges of the full order, so a group of any size is
spread; what a border needs from the range before it is one row a range. Joins back to suffixes are
plain equi-joins that Spark may split at hot keys. A suffix leaves the doubling as soon as its rank is
its own.

Defined cases: null text has no lines; lines without a word are never deleted and do not part a run;
rows with a null key keep all lines and are no first copy; rows equal in key and text are one
document and treated alike; equal keys with other texts are ordered by a digest of the text; texts
are taken whole; an empty table gives no rows; extra columns pass through `deduped`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from foldstar.llm.shared import filtered, released, settled, stored, table

MIN_LINES = 2
#: Words from which a repeated line alone is a run.
SINGLE_WORDS = 5
SUFFIX = ["_k", "_r", "n"]


def _split(text) -> F.Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _worded(line) -> F.Column:
    return line.rlike(r"[^ \t-\r]")


def _long(line, n: int) -> F.Column:
    """Whether a line has `n` words or more."""
    return line.rlike(rf"^[ \t-\r]*(?:[^ \t-\r]+[ \t-\r]+){{{n - 1}}}[^ \t-\r]")


def suffixes(docs: DataFrame, key: str, text: str, single_words: int | None = None) -> DataFrame:
    """Columns _k, _r (digest of the text), n (place among lines with a word), left (such lines from here on), i (place among all), alone (long enough to be a run), d1, d2."""
    t = F.col(f"`{text}`")
    filled = F.filter(F.transform(_split(t), lambda x, i: F.struct(i.alias("i"), x.alias("x"))), lambda s: _worded(s["x"]))
    lines = docs.where(F.col(f"`{key}`").isNotNull() & t.isNotNull()).select(F.col(f"`{key}`").alias("_k"), F.xxhash64(t).alias("_r"), filled.alias("f"))
    rows = lines.select("_k", "_r", F.size("f").alias("all"), F.posexplode("f").alias("n", "s"))
    alone = F.lit(False) if single_words is None else _long(F.col("s.x"), single_words)
    # the literal comes first in d2, so that its seed, and not the digest before it, sets the two apart
    return rows.select("_k", "_r", "n", (F.col("all") - F.col("n")).alias("left"), F.col("s.i").alias("i"), alone.alias("alone"), F.xxhash64("s.x").alias("d1"), F.xxhash64(F.lit(1), "s.x").alias("d2"))


def _dealt(rows: DataFrame, keys: list[str], tag: str) -> DataFrame:
    """`rows` written in ranges of `keys`, with the number `p` of their range."""
    return stored(rows.repartitionByRange(*keys).withColumn("p", F.spark_partition_id()), tag)


def ranked(counts: DataFrame, keys: list[str], depth: int) -> tuple[DataFrame, int]:
    """Distinct `keys` with counts c: `before`, rows with smaller keys; `open`, whether more lines can part its rows; `ahead`, open rows with smaller keys.

    Also the number of open rows. `left` is the number of lines that the rows of a key have.
    """
    dealt = _dealt(counts.withColumn("open", (F.col("c") > 1) & (F.col("left") >= depth)).drop("left"), keys, "line-keys")
    going = F.when(F.col("open"), F.col("c")).otherwise(0)
    sums, base, b, g = dealt.groupBy("p").agg(F.sum("c").alias("b"), F.sum(going).alias("g")).collect(), [], 0, 0  # one row a range
    for r in sorted(sums, key=lambda r: r["p"]):
        base.append((r["p"], b, g))
        b, g = b + r["b"], g + r["g"]
    inside = Window.partitionBy("p").orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
    placed = dealt.withColumns({"x": F.coalesce(F.sum("c").over(inside), F.lit(0)), "y": F.coalesce(F.sum(going).over(inside), F.lit(0))})
    known = dealt.sparkSession.createDataFrame(base, "p int, b long, g long")
    out = stored(placed.join(F.broadcast(known), "p").select(*keys, "c", "open", (F.col("b") + F.col("x")).alias("before"), (F.col("g") + F.col("y")).alias("ahead")), "line-ranks")
    released(dealt)
    return out, g


def ranks(lines: DataFrame) -> DataFrame:
    """Columns of SUFFIX, left, i, alone, rank in the full order, and `seen`: ranks by 1, 2, 4, ... lines while these were shared."""
    size = [F.count("*").alias("c"), F.max("left").alias("left")]
    keep = [*SUFFIX, "left", "i", "alone"]
    none = F.array().cast("array<bigint>")
    keyed, going = ranked(lines.groupBy("d1", "d2").agg(*size), ["d1", "d2"], 1)
    first = F.when(F.col("c") > 1, F.array("before")).otherwise(none).alias("seen")
    now = stored(lines.join(keyed, ["d1", "d2"]).select(*keep, F.col("before").alias("rank"), "open", "ahead", first), "suffixes")
    released(keyed)
    depth, parts = 1, [now]
    while going:
        behind = None
        for k in parts:
            k = k.where(F.col("n") >= depth).select("_k", "_r", (F.col("n") - depth).alias("n"), F.col("rank").alias("second"))
            behind = k if behind is None else behind.unionByName(k)
        parts[-1] = now.where(~F.col("open"))
        pairs = stored(now.where("open").drop("open").join(behind.hint("merge"), SUFFIX, "left").withColumn("second", F.coalesce("second", F.lit(-1).cast("long"))), "suffix-pairs")
        depth *= 2
        # whole groups of a rank are open, so what is ahead of a group is ahead of the pairs that part it
        step, going = ranked(pairs.groupBy("rank", "second").agg(*size), ["rank", "second"], depth)
        moved = F.col("rank") + F.col("before") - F.col("past")
        longer = F.when(F.col("open"), F.concat("seen", F.array(moved))).otherwise(F.col("seen")).alias("seen")
        now = stored(pairs.withColumnRenamed("ahead", "past").join(step, ["rank", "second"]).select(*keep, moved.alias("rank"), "open", "ahead", longer), "suffixes")
        released(pairs, step)
        parts.append(now)
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out.drop("open", "ahead")


def _levels(a, b):
    """How many ranks two suffixes have in common."""
    return F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda e: e))


def prefixes(order: DataFrame) -> DataFrame:
    """The suffixes that share their first line with another: columns of `order`, p, and `lcp`, the lines each has in common with the one before it.

    Rows are in the order of (p, rank, _k, _r, n); equal suffixes follow each other by document and place.
    """
    by = ["rank", *SUFFIX]
    dealt = _dealt(order.where(F.size("seen") > 0), by, "suffix-array")
    inside = Window.partitionBy("p").orderBy(*by)
    last = dealt.groupBy("p").agg(F.max(F.struct(*by, "seen")).alias("last"))  # one row a range
    border = last.select("p", F.lag("last").over(Window.orderBy("p")).alias("border"))
    met = dealt.withColumn("b", F.lag(F.struct(*by, "seen")).over(inside)).join(F.broadcast(border), "p").withColumn("b", F.coalesce("b", "border")).drop("border")
    shared = F.coalesce(_levels(F.col("seen"), F.col("b.seen")), F.lit(0))
    first = stored(met.select("*", F.when(F.col("b.rank") == F.col("rank"), -1).otherwise(shared).alias("levels"), F.col("b._k").alias("_bk"), F.col("b._r").alias("_br"), F.col("b.n").alias("bn")).drop("b"), "neighbours")
    released(dealt)
    power = lambda c: F.when(c > 0, F.pow(F.lit(2), c - 1).cast("int")).otherwise(0)
    told = first.where("levels < 2").select("p", *by, F.when(F.col("levels") < 0, F.col("left")).otherwise(F.col("levels")).alias("lcp"))
    going = first.where("levels > 1").select("p", *by, "_bk", "_br", "bn", power(F.col("levels")).alias("lcp"))
    known = first.select("_k", "_r", "n", "seen")
    while not going.isEmpty():
        a = known.toDF("_k", "_r", "an", "sa")
        b = known.toDF("_bk", "_br", "bm", "sb")
        at = going.withColumns({"an": F.col("n") + F.col("lcp"), "bm": F.col("bn") + F.col("lcp")})
        both = at.join(a.hint("merge"), ["_k", "_r", "an"], "left").join(b.hint("merge"), ["_bk", "_br", "bm"], "left")
        more = F.coalesce(_levels(F.col("sa"), F.col("sb")), F.lit(0))
        step = stored(both.select("p", *by, "_bk", "_br", "bn", (F.col("lcp") + power(more)).alias("lcp"), more.alias("levels")), "neighbours")
        told = told.unionByName(step.where("levels < 2").select("p", *by, "lcp"))
        going = step.where("levels > 1").drop("levels")
    return stored(first.drop("levels", "_bk", "_br", "bn").join(told.drop("p", "rank").hint("merge"), SUFFIX), "prefixes")


def intervals(array: DataFrame, least: dict[str, int]) -> DataFrame:
    """`array` (see prefixes) with a number for each name in `least`, one for neighbours in an unbroken row of so many common lines."""
    inside = Window.partitionBy("p").orderBy("rank", *SUFFIX).rowsBetween(Window.unboundedPreceding, 0)
    out = array.withColumns({name: F.sum((F.col("lcp") < m).cast("long")).over(inside) for name, m in least.items()})
    earlier = Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)
    heads = array.groupBy("p").agg(*[F.sum((F.col("lcp") < m).cast("long")).alias(name) for name, m in least.items()])  # one row a range
    before = heads.select("p", *[F.coalesce(F.sum(name).over(earlier), F.lit(0)).alias(f"_{name}") for name in least])
    return out.join(F.broadcast(before), "p").withColumns({name: F.col(name) + F.col(f"_{name}") for name in least}).drop(*[f"_{name}" for name in least])


def _array(docs: DataFrame, key: str, text: str, single_words: int | None = None) -> DataFrame:
    lines = stored(suffixes(docs, key, text, single_words).dropDuplicates(SUFFIX), "lines")
    order = ranks(lines)
    released(lines)
    return prefixes(order)


def runs(docs: DataFrame, key: str = "doc_id", text: str = "text", min_lines: int = MIN_LINES) -> DataFrame:
    """Maximal repeated runs: _k, i (place of the first line among all), length in lines, run (equal for equal runs), copies.

    A row is a place whose longest repeated run is not the tail of the run of the line before; copies are the
    places where exactly this run is the longest repeated one. A run that only occurs inside longer ones has no row.
    """
    array = _array(docs, key, text)
    inside = Window.partitionBy("p").orderBy("rank", *SUFFIX)
    first = array.groupBy("p").agg(F.min_by("lcp", F.struct("rank", *SUFFIX)).alias("next"))
    border = first.select("p", F.lead("next").over(Window.orderBy("p")).alias("next"))
    ends = array.withColumn("after", F.lead("lcp").over(inside)).join(F.broadcast(border), "p")
    longest = stored(ends.select(*SUFFIX, "i", "seen", F.greatest("lcp", F.coalesce("after", "next", F.lit(0))).alias("length")), "longest")
    # a run is told by the ranks of its first and of its last 2**j lines, 2**j being the largest power within it
    j = F.floor(F.log2("length") + F.lit(1e-9)).cast("int")
    size = F.pow(F.lit(2), j).cast("int")
    tails = longest.select("_k", "_r", F.col("n").alias("_m"), F.col("seen").alias("tail"))
    named = longest.where(F.col("length") >= min_lines).withColumn("_m", F.col("n") + F.col("length") - size).join(tails, ["_k", "_r", "_m"])
    named = named.select(*SUFFIX, "i", "length", F.xxhash64("length", F.get("seen", j), F.get("tail", j)).alias("run"))
    counts = stored(named.groupBy("run").agg(F.count("*").alias("copies")), "run-copies")
    front = longest.select("_k", "_r", (F.col("n") + 1).alias("n"), F.col("length").alias("front"))
    return named.join(front, SUFFIX, "left").where("front is null or front <= length").join(counts, "run").select("_k", "i", "length", "run", "copies")


def _later(array: DataFrame, interval: str) -> DataFrame:
    """The members of each interval but its first copy."""
    start = F.struct(*SUFFIX)
    first = stored(array.groupBy(interval).agg(F.count("*").alias("c"), F.min(start).alias("first")).where("c > 1").drop("c"), "first-copies")
    return array.join(first, interval).where(start != F.col("first"))


def _deleted(docs: DataFrame, key: str, text: str, min_lines: int, single_words: int | None = None) -> DataFrame:
    """Columns _k, _r, gone: places among all lines of the lines to delete."""
    array = _array(docs, key, text, single_words)
    cut = stored(intervals(array, {"long": min_lines, "one": 1}).drop("p", "rank", "seen", "left"), "intervals")
    later = _later(cut, "long").select(*SUFFIX)
    covered = later.select("_k", "_r", F.explode(F.sequence(F.col("n"), F.col("n") + min_lines - 1)).alias("n"))
    if single_words is not None:
        covered = covered.unionByName(_later(cut.where("alone"), "one").select(*SUFFIX))
    # a deleted line is repeated, so it starts a suffix of the array
    return cut.join(covered.distinct(), SUFFIX, "left_semi").groupBy("_k", "_r").agg(F.collect_list("i").alias("gone"))


def _judged(docs: DataFrame, key: str, text: str, min_lines: int, single_words: int | None = None) -> DataFrame:
    """_row (all columns of `docs`), _kept (text without deleted lines), _n and _gone (counts of lines with a word)."""
    t = F.col(f"`{text}`")
    gone = settled(lambda: _deleted(docs, key, text, min_lines, single_words), "deleted-lines")
    others = [F.col(f"`{c}`") for c in docs.columns if c != text]
    source = docs.select(F.struct(*others, F.lit(0).alias("_fill")).alias("_row"), F.col(f"`{key}`").alias("_k"), F.xxhash64(t).alias("_r"), t.alias("_t"))
    # a merge join at every size: `gone` grows with the corpus, so it is never broadcast
    met = source.join(gone.hint("merge"), ["_k", "_r"], "left").select("_row", "_t", "gone", F.when(F.col("_t").isNotNull(), _split(F.col("_t"))).alias("_l"))
    stay = F.array_except(F.sequence(F.lit(0), F.size("_l") - 1), F.col("gone"))
    kept = F.when(F.col("gone").isNull(), F.col("_t")).otherwise(F.array_join(F.transform(stay, lambda i: F.get(F.col("_l"), i)), "\n"))
    n = F.coalesce(F.size(F.filter(F.col("_l"), _worded)), F.lit(0)).cast("long")
    return met.select("_row", kept.alias("_kept"), F.when(F.col("_t").isNull(), F.lit(0).cast("long")).otherwise(n).alias("_n"), F.when(F.col("gone").isNull(), 0).otherwise(F.size("gone")).cast("long").alias("_gone"))


def summary(docs: DataFrame, key: str = "doc_id", text: str = "text", min_lines: int = MIN_LINES, single_words: int | None = SINGLE_WORDS) -> DataFrame:
    """Per row: key, n_lines, n_removed (lines with a word), kept_sha256 of the text that stays (null: null)."""
    j = _judged(docs, key, text, min_lines, single_words)
    return j.select(F.col("_row").getField(key).alias(key), F.col("_n").alias("n_lines"), F.col("_gone").alias("n_removed"), F.sha2(F.encode("_kept", "UTF-8"), 256).alias("kept_sha256"))


def deduped(docs: DataFrame, key: str = "doc_id", text: str = "text", min_lines: int = MIN_LINES, single_words: int | None = SINGLE_WORDS) -> DataFrame:
    """`docs` without the lines of later copies; rows that lose every line with a word go."""
    j = filtered(_judged(docs, key, text, min_lines, single_words), (F.col("_gone") == 0) | (F.col("_gone") < F.col("_n")))
    return j.select(*[F.col("_kept").alias(c) if c == text else F.col("_row").getField(c).alias(c) for c in docs.columns])


def op4_line_dedup(spark, sf_dir: str) -> DataFrame:
    return summary(table(spark, sf_dir, "documents").select("doc_id", "text"))


OP4_SQL = rf"""
WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS x, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM documents),
f AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS n FROM l WHERE regexp_matches(x, '[^ \t-\r]')),
w AS (SELECT doc_id, n, list(x) OVER (PARTITION BY doc_id ORDER BY n ROWS BETWEEN CURRENT ROW AND {MIN_LINES - 1} FOLLOWING) AS g FROM f),
later AS (SELECT doc_id, n FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY doc_id, n) AS c FROM w WHERE len(g) = {MIN_LINES}) WHERE c > 1),
one AS (SELECT doc_id, n FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY doc_id, n) AS c FROM f
    WHERE regexp_matches(x, '^[ \t-\r]*([^ \t-\r]+[ \t-\r]+){{{SINGLE_WORDS - 1}}}[^ \t-\r]')) WHERE c > 1),
gone AS (SELECT doc_id, n FROM one UNION SELECT doc_id, n + k AS n FROM later, (SELECT unnest(range({MIN_LINES})) AS k)),
gi AS (SELECT f.doc_id, f.i FROM f JOIN gone USING (doc_id, n)),
stay AS (SELECT doc_id, string_agg(x, chr(10) ORDER BY i) AS t FROM l ANTI JOIN gi USING (doc_id, i) GROUP BY doc_id),
nf AS (SELECT doc_id, count(*) AS n FROM f GROUP BY doc_id),
ng AS (SELECT doc_id, count(*) AS n FROM gi GROUP BY doc_id)
SELECT d.doc_id, coalesce(nf.n, 0)::BIGINT AS n_lines, coalesce(ng.n, 0)::BIGINT AS n_removed,
       CASE WHEN d.text IS NOT NULL THEN sha256(coalesce(stay.t, '')) END AS kept_sha256
FROM documents d LEFT JOIN stay USING (doc_id) LEFT JOIN nf USING (doc_id) LEFT JOIN ng USING (doc_id)"""
