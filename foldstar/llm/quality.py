"""Quality rules: a table of thresholds compiled into one projection of built-in functions.

A rule names a measure and the closed interval of values it allows. `compile_rules` turns the
table into one boolean Column; `measures` builds the measures. No user function runs: every row is
evaluated where it is scanned, nothing is shuffled, and a document costs time n log n in its words.

Defined cases: a null text counts as empty; an empty text has zero words and fails the base rule;
words are what lies between spaces and control characters 9 to 13, so a text of any length, without
line breaks or without spaces, is taken whole; equal rows are judged alike; columns of the input
other than the text are passed on as they are, and measures are kept apart in one struct so that no
name clashes.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import filtered, table, words

# Characters counted as symbols.
SYMBOLS = "#*$%&|<>"

# Frequent function words of four languages.
STOP_WORDS = (
    "the be to of and that have with is in it for was as by this are on or at from",
    "der die das und ist in zu den von mit ein eine auf für im nicht",
    "le la les de et est un une des en que du dans pour sur au",
    "el la los las de y es un una en que del por con para se",
)


@dataclass(frozen=True)
class Rule:
    """Keeps a document if low <= measure <= high (an open side is None)."""

    measure: str
    low: float | None = None
    high: float | None = None


#: Production thresholds. Ratios are per word unless the name says lines.
RULES = (
    Rule("n_words", 50, None),
    Rule("mean_word_chars", 2.0, 12.0),
    Rule("symbol_ratio", None, 0.10),
    Rule("dup_line_ratio", None, 0.50),
    Rule("stop_word_count", 2, None),
    Rule("upper_ratio", None, 0.50),
    Rule("digit_ratio", None, 0.50),
    Rule("bang_ratio", None, 0.20),
    Rule("ellipsis_line_ratio", None, 0.30),
    Rule("bullet_line_ratio", None, 0.90),
)

BASE_MIN_WORDS = 50
BASE_REPEAT_PERCENT = 50


#: Low bits of a window's key that hold its place; texts with more windows take the slower exact way.
PLACE_BITS = 20
_PLACE = (1 << PLACE_BITS) - 1


def _window_keys(w: Column) -> Column:
    """One long for each three-word window: high bits of its digest, then its place; sorted."""
    starts = F.when(F.size(w) < 4, F.array().cast("array<int>")).otherwise(F.sequence(F.lit(0), F.size(w) - 3))
    key = lambda i: F.xxhash64(w[i], w[i + 1], w[i + 2]).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(i.cast("long"))
    return F.sort_array(F.transform(starts, key))


def _same_digest(a: Column, b: Column) -> Column:
    return F.shiftrightunsigned(a.bitwiseXOR(b), PLACE_BITS) == 0


def _suspects(s: Column) -> Column:
    """The keys that share their digest with a neighbour, still sorted."""
    return F.filter(s, lambda x, k: ((k > 0) & _same_digest(x, F.get(s, k - 1))) | ((k < F.size(s) - 1) & _same_digest(x, F.get(s, k + 1))))


def _covered(places: Column) -> Column:
    """Words in the union of three-word windows at these sorted places."""
    zero = F.struct(F.lit(0).cast("long").alias("end"), F.lit(0).cast("long").alias("n"))
    step = lambda a, i: F.struct((i + 3).alias("end"), (a["n"] + (i + 3 - F.greatest(a["end"], i))).alias("n"))
    return F.aggregate(places, zero, step, lambda a: a["n"])


def _repeat_words(w: Column, t: Column) -> Column:
    """How many words lie in a three-word window that is found twice or more.

    `t` holds the windows whose digests met a neighbour's. Where all of them are equal word for
    word to such a neighbour (nearly always), their places are swept once. A clash of digests, or a
    text too long for the keys, sends that text to a sort by the windows themselves.
    """
    place = lambda x: x.bitwiseAND(F.lit(_PLACE)).cast("int")
    word_equal = lambda i, j: (w[i] == w[j]) & (w[i + 1] == w[j + 1]) & (w[i + 2] == w[j + 2])
    clash = F.exists(F.sequence(F.lit(1), F.size(t) - 1), lambda k: _same_digest(F.get(t, k), F.get(t, k - 1)) & ~word_equal(place(F.get(t, k)), place(F.get(t, k - 1))))
    quick = _covered(F.sort_array(F.transform(t, lambda x: x.bitwiseAND(F.lit(_PLACE)))))
    text_at = lambda i: F.concat_ws(" ", w[i], w[i + 1], w[i + 2])
    by_text = F.sort_array(F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.struct(text_at(i).alias("t"), i.cast("long").alias("i"))))
    twins = lambda s: F.filter(s, lambda x, k: ((k > 0) & (x["t"] == F.get(s, k - 1)["t"])) | ((k < F.size(s) - 1) & (x["t"] == F.get(s, k + 1)["t"])))
    # a transform over a one-element array binds the sorted windows: sorted once, read often
    slow = F.transform(F.array(by_text), lambda s: _covered(F.sort_array(F.transform(twins(s), lambda x: x["i"]))))[0]
    none = F.lit(0).cast("long")
    return F.when(F.size(w) < 4, none).when(F.size(w) > _PLACE, slow).when(F.size(t) < 2, none).when(clash, slow).otherwise(quick)


def measures(df: DataFrame, text: str = "text", into: str = "_m") -> DataFrame:
    """Add a struct column `into` with the base counts and the ratios that rules may name."""
    raw = F.col(f"`{text}`")
    own = [F.col(f"`{c}`") for c in df.columns]
    bound = df.select(F.struct(*own).alias("_row"), F.coalesce(raw, F.lit("")).alias("_text"))
    bound = bound.select("*", words(F.col("_text")).alias("_w"), F.filter(F.split("_text", "\n", -1), lambda x: x.rlike(r"[^ \t-\r]")).alias("_fl"))
    bound = bound.select("*", _window_keys(F.col("_w")).alias("_s"))
    bound = bound.select(*[c for c in bound.columns if c != "_s"], _suspects(F.col("_s")).alias("_t"))
    t, w = F.col("_text"), F.col("_w")
    stop = F.array(*[F.lit(s) for s in sorted({f for group in STOP_WORDS for s in group.split() for f in (s, s.capitalize())})])
    without = lambda pattern: F.length(t) - F.length(F.regexp_replace(t, pattern, ""))
    counted = bound.select(
        "_row",
        "_fl",
        F.size(w).cast("long").alias("_n"),
        F.length(F.array_join(w, "")).cast("long").alias("_chars"),
        without(f"[{SYMBOLS}]+").cast("long").alias("_sym"),
        _repeat_words(w, F.col("_t")).alias("_rep"),
        F.size(F.array_intersect(w, stop)).cast("long").alias("_stop"),
        without(r"\p{Lu}+").alias("_up"),
        without(r"[0-9]+").alias("_digits"),
        without(r"[!?]+").alias("_bang"),
        (F.size("_fl") - F.size(F.array_distinct("_fl"))).cast("long").alias("_dup"),
    )
    fl, n, n_lines = F.col("_fl"), F.greatest(F.col("_n"), F.lit(1)), F.greatest(F.size("_fl"), F.lit(1))
    chars = F.greatest(F.col("_chars"), F.lit(1))
    made = F.struct(
        F.col("_n").alias("n_words"),
        F.col("_chars").alias("word_chars"),
        F.col("_sym").alias("n_symbols"),
        F.col("_dup").alias("n_dup_lines"),
        F.col("_rep").alias("n_repeat_words"),
        (F.col("_chars") / n).alias("mean_word_chars"),
        (F.col("_sym") / n).alias("symbol_ratio"),
        (F.col("_dup") / n_lines).alias("dup_line_ratio"),
        F.col("_stop").alias("stop_word_count"),
        (F.col("_up") / chars).alias("upper_ratio"),
        (F.col("_digits") / chars).alias("digit_ratio"),
        (F.col("_bang") / n).alias("bang_ratio"),
        (F.size(F.filter(fl, lambda x: x.rlike(r"(\.\.\.|…)\s*$"))) / n_lines).alias("ellipsis_line_ratio"),
        (F.size(F.filter(fl, lambda x: x.rlike(r"^\s*[-•*·]"))) / n_lines).alias("bullet_line_ratio"),
    )
    row = [F.col("_row").getField(c).alias(c) for c in df.columns]
    return counted.select(*row, made.alias(into))


def compile_rules(rules=RULES, of: str = "_m") -> Column:
    """One boolean Column: true if every rule's measure lies in its interval."""
    verdict = F.lit(True)
    for r in rules:
        m = F.col(f"{of}.{r.measure}")
        if r.low is not None:
            verdict = verdict & (m >= F.lit(r.low))
        if r.high is not None:
            verdict = verdict & (m <= F.lit(r.high))
    return verdict


def base_failed(of: str = "_m") -> Column:
    n, rep = F.col(f"{of}.n_words"), F.col(f"{of}.n_repeat_words")
    return (n < BASE_MIN_WORDS) | (100 * rep > BASE_REPEAT_PERCENT * n)


def judge(df: DataFrame, rules=RULES, text: str = "text", into: str = "_m") -> DataFrame:
    """`df` with the struct of measures, `base_failed` and `kept` in it."""
    m = measures(df, text, into)
    bad = base_failed(into)
    return m.withColumn(into, F.struct(f"{into}.*", bad.alias("base_failed"), (~bad & compile_rules(rules, into)).alias("kept")))


def keep_good(df: DataFrame, rules=RULES, text: str = "text") -> DataFrame:
    """The rows of `df` that pass, with the columns of `df`."""
    into = "_m"
    while into in df.columns:
        into += "_"
    return filtered(judge(df, rules, text, into), F.col(f"{into}.kept")).select(*[F.col(f"`{c}`") for c in df.columns])


def op5_quality_rules(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return judge(docs).select("doc_id", "_m.n_words", "_m.word_chars", "_m.n_symbols", "_m.n_dup_lines", "_m.n_repeat_words", "_m.base_failed", "_m.kept")


def _oracle() -> str:
    """DuckDB SQL for the same rows: windows by joins and counts instead of sorted digests."""
    gap = r"[ \t-\r]+"
    stops = ", ".join(f"'{f}'" for f in sorted({f for g in STOP_WORDS for s in g.split() for f in (s, s.capitalize())}))
    tests = [f"{r.measure} >= {r.low}" for r in RULES if r.low is not None] + [f"{r.measure} <= {r.high}" for r in RULES if r.high is not None]
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
b AS (SELECT doc_id, t, list_filter(regexp_split_to_array(t, '{gap}'), lambda x: x <> '') AS w,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ \t-\r]')) AS fl FROM d),
win AS (SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g
        FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM b)),
twice AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
rep AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS k) GROUP BY doc_id),
m AS (SELECT b.doc_id, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars,
        length(t) - length(regexp_replace(t, '[{SYMBOLS}]', '', 'g')) AS n_symbols,
        len(fl) - len(list_distinct(fl)) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words,
        greatest(len(w), 1) AS nw, greatest(len(fl), 1) AS nl, greatest(length(array_to_string(w, '')), 1) AS nc,
        len(list_intersect(list_distinct(w), [{stops}])) AS stop_word_count,
        length(t) - length(regexp_replace(t, '\p{{Lu}}', '', 'g')) AS up,
        length(t) - length(regexp_replace(t, '[0-9]', '', 'g')) AS dig,
        length(t) - length(regexp_replace(t, '[!?]', '', 'g')) AS bang,
        len(list_filter(fl, lambda x: regexp_matches(x, '(\.\.\.|…)\s*$'))) AS el,
        len(list_filter(fl, lambda x: regexp_matches(x, '^\s*[-•*·]'))) AS bu
      FROM b LEFT JOIN rep USING (doc_id)),
r AS (SELECT *, word_chars / nw AS mean_word_chars, n_symbols / nw AS symbol_ratio, n_dup_lines / nl AS dup_line_ratio,
        up / nc AS upper_ratio, dig / nc AS digit_ratio, bang / nw AS bang_ratio, el / nl AS ellipsis_line_ratio, bu / nl AS bullet_line_ratio,
        (n_words < {BASE_MIN_WORDS} OR 100 * n_repeat_words > {BASE_REPEAT_PERCENT} * n_words) AS base_failed FROM m)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
       n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, base_failed,
       NOT base_failed AND {' AND '.join(tests)} AS kept
FROM r"""


OP5_SQL = _oracle()
