"""Substring dedup: recurring passages compiled into sharded Aho-Corasick automata.

A window is `window` consecutive words. Words go that lie in a window which also starts in a document
with a smaller key; windows are judged on the input. Steps:

1. Anchors. The anchor of a window is the least digest among its word grams of length `gram`. Equal
   windows have equal anchors, and a document has an anchor for every dozen words or two, so anchors
   found in two documents mark every place where a window can recur.
2. Confirmation. Runs of windows with such anchors are cut out as fragments, and windows are grouped
   by 128-bit digest: those of two documents or more recur, and the smallest key owns them. Runs of
   windows of one owner are its passages; the passages hold each recurring window once.
3. Automata. Passages are cut into aligned blocks of half a window (every window in a passage holds
   a whole block). A shard of owners gets one Aho-Corasick automaton of its blocks; the fragments of
   all documents that share a window with an owner of the shard stream through it. A hit is extended
   word by word, left and right, against the passage: removal rests on equal words, not on digests.

Nothing grows with a group's size in one task: digests are aggregated map-side, a document meets a
shard once, and a shard with many documents is dealt to several tasks, each with its own copy of the
automaton.

Defined cases: null and empty texts and texts shorter than a window lose nothing; rows with a null
key lose nothing and own nothing; rows with equal keys are one document as owner and are cleaned row
by row; texts are taken whole; an empty table gives no rows; extra columns pass through `cleaned`.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import partitions, released, settled, ship, stored, table

WINDOW = 50
GRAM = 16
SHARD_WORDS = 100_000
SHARD_ROWS = 1_000

_GAP = np.zeros(256, dtype=bool)
_GAP[[9, 10, 11, 12, 13, 32]] = True
_U = np.uint64
_BASES = (_U(0x9E3779B97F4A7C15 | 1), _U(0xC2B2AE3D27D4EB4F), _U(0x165667B19E3779F9))
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(which: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base modulo 2**64 and of its inverse, n of them at least."""
    have = _POWERS.get(which)
    if have is None or len(have[0]) < n:
        size = max(1 << 14, 1 << int(n).bit_length())
        base = _BASES[which]
        up, down = np.full(size, base, dtype=_U), np.full(size, _U(pow(int(base), -1, 1 << 64)), dtype=_U)
        up[0] = down[0] = 1
        have = _POWERS[which] = (np.cumprod(up, dtype=_U), np.cumprod(down, dtype=_U))
    return have


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U(33))) * _U(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> _U(29))) * _U(0xC4CEB9FE1A85EC53)
    return h ^ (h >> _U(32))


def word_spans(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Byte starts and ends of the words of a UTF-8 text."""
    gap = np.ones(len(data) + 2, dtype=bool)
    gap[1:-1] = _GAP[np.frombuffer(data, dtype=np.uint8)]
    turn = np.flatnonzero(gap[1:] != gap[:-1])
    return turn[::2], turn[1::2]


def _rolled(x: np.ndarray, length: int, which: int) -> np.ndarray:
    up, down = _powers(which, len(x))
    sums = np.zeros(len(x) + 1, dtype=_U)
    np.cumsum(x * up[: len(x)], dtype=_U, out=sums[1:])
    return _mix((sums[length:] - sums[:-length]) * down[: len(x) - length + 1])


def word_digests(data: bytes, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    up, down = _powers(0, len(data))
    sums = np.zeros(len(data) + 1, dtype=_U)
    np.cumsum((np.frombuffer(data, dtype=np.uint8).astype(_U) + _U(1)) * up[: len(data)], dtype=_U, out=sums[1:])
    return _mix((sums[ends] - sums[starts]) * down[starts])


def anchors(words: np.ndarray, window: int, gram: int) -> np.ndarray:
    """For each window, the least digest of its grams (signed)."""
    g = _rolled(words, gram, 1)
    span, low, have = window - gram + 1, g, 1
    while have < span:
        step = min(have, span - have)
        low = np.minimum(low[:-step], low[step:])
        have += step
    return low.view(np.int64)


def _read(t: str | None):
    data = (t or "").encode("utf-8", "replace")
    return data, *word_spans(data)


def _fragments(docs: DataFrame, window: int, gram: int) -> DataFrame:
    """Columns _k, _r, at, body: the runs of words in which windows may recur elsewhere."""

    def scan(frames):
        for f in frames:
            keys, rows, found = [], [], []
            for k, r, t in zip(f["_k"], f["_r"], f["_t"]):
                data, s, e = _read(t)
                if len(s) >= window:
                    a = np.unique(anchors(word_digests(data, s, e), window, gram))
                    keys.append(np.full(len(a), k))
                    rows.append(np.full(len(a), r))
                    found.append(a)
            if found:
                yield pd.DataFrame({"_k": np.concatenate(keys), "_r": np.concatenate(rows), "a": np.concatenate(found)})

    def cut(frames):
        for f in frames:
            out = []
            for k, r, t, near in zip(f["_k"], f["_r"], f["_t"], f["near"]):
                data, s, e = _read(t)
                ok = np.zeros(len(s) - window + 3, dtype=bool)
                ok[1:-1] = np.isin(anchors(word_digests(data, s, e), window, gram), np.asarray(near))
                turn = np.flatnonzero(ok[1:] != ok[:-1])
                for i, j in zip(turn[::2].tolist(), turn[1::2].tolist()):
                    w = data[s[i] : e[j + window - 2]].split()
                    out.append((k, r, i, b" ".join(w).decode("utf-8", "replace")))
            yield pd.DataFrame(out, columns=["_k", "_r", "at", "body"])

    known = docs.where(F.col("_k").isNotNull() & (F.length("_t") >= 2 * window - 1))
    def fragments():
        marks = stored(known.mapInPandas(scan, "_k long, _r long, a long"), "anchors")
        twice = marks.groupBy("a").agg(F.min("_k").alias("lo"), F.max("_k").alias("hi")).where("lo < hi").select("a")
        near = marks.join(twice, "a").groupBy("_k", "_r").agg(F.collect_list("a").alias("near"))
        return known.join(near.hint("merge"), ["_k", "_r"]).mapInPandas(cut, "_k long, _r long, at long, body string")

    return settled(fragments, "fragments")


def _digest_pairs(body: str, window: int) -> tuple[np.ndarray, np.ndarray]:
    data = body.encode("utf-8", "replace")
    s, e = word_spans(data)
    w = word_digests(data, s, e)
    return _rolled(w, window, 1).view(np.int64), _rolled(_mix(w + _U(0x5851F42D4C957F2D)), window, 2).view(np.int64)


def _owned(fragments: DataFrame, window: int) -> tuple[DataFrame, DataFrame]:
    """Passages (owner, at, body), and which row shares windows with which smaller owner."""

    def digests(frames):
        for f in frames:
            keys, rows, d1, d2 = [], [], [], []
            for k, r, body in zip(f["_k"], f["_r"], f["body"]):
                a, b = _digest_pairs(body, window)
                keys.append(np.full(len(a), k))
                rows.append(np.full(len(a), r))
                d1.append(a)
                d2.append(b)
            if d1:
                yield pd.DataFrame({"_k": np.concatenate(keys), "_r": np.concatenate(rows), "d1": np.concatenate(d1), "d2": np.concatenate(d2)})

    def runs(frames):
        for f in frames:
            out = []
            for k, at, body, own in zip(f["_k"], f["at"], f["body"], f["own"]):
                mine = {(x["d1"], x["d2"]) for x in own}
                a, b = _digest_pairs(body, window)
                ok = np.zeros(len(a) + 2, dtype=bool)
                ok[1:-1] = [p in mine for p in zip(a.tolist(), b.tolist())]
                turn = np.flatnonzero(ok[1:] != ok[:-1])
                w = body.split(" ")
                for i, j in zip(turn[::2].tolist(), turn[1::2].tolist()):
                    out.append((k, at + i, " ".join(w[i : j + window - 1])))
            yield pd.DataFrame(out, columns=["owner", "at", "body"])

    windows = fragments.mapInPandas(digests, "_k long, _r long, d1 long, d2 long")
    shared = stored(windows.groupBy("d1", "d2").agg(F.min("_k").alias("owner"), F.max("_k").alias("hi")).where("owner < hi").select("d1", "d2", "owner"), "windows")
    met = stored(windows.join(shared, ["d1", "d2"]).where("owner < _k").select("_k", "_r", "owner").distinct(), "meetings")
    own = shared.groupBy(F.col("owner").alias("_k")).agg(F.collect_list(F.struct("d1", "d2")).alias("own"))
    passages = stored(fragments.join(own, "_k").mapInPandas(runs, "owner long, at long, body string"), "passages")
    released(shared)
    return passages.dropDuplicates(["owner", "at", "body"]), met


def _automaton(passages: list[tuple[int, list[str]]], block: int):
    """Blocks of the passages to {owner: [(passage, offset)]}."""
    import ahocorasick

    places: dict[str, dict[int, list[tuple[int, int]]]] = {}
    for n, (owner, w) in enumerate(passages):
        for o in range(0, len(w) - block + 1, block):
            places.setdefault(" " + " ".join(w[o : o + block]) + " ", {}).setdefault(owner, []).append((n, o))
    auto = ahocorasick.Automaton()
    for phrase, where in places.items():
        auto.add_word(phrase, (len(phrase), where))
    auto.make_automaton()
    return auto


def _ranges(auto, passages, key: int, body: str, owners: set[int], window: int) -> list[tuple[int, int]]:
    """Ranges of words of `body` that equal a stretch, a window long at least, of an owner's passage."""
    text = f" {body} "
    w = body.split(" ")
    place: dict[int, int] = {}
    at = 0
    for i, x in enumerate(w):
        place[at] = i
        at += len(x) + 1
    done: dict[tuple[int, int], int] = {}
    out = []
    a = b = 0  # the last range found
    for end, (size, where) in auto.iter(text):
        i = place[end - size + 1]
        for owner in owners & where.keys() if len(owners) <= len(where) else [o for o in where if o in owners]:
            for n, o in where[owner]:
                if done.get((n, i - o), -1) > i:
                    continue
                p = passages[n][1]
                if a <= i < b:
                    # inside a range already found: only a match at one of its borders can reach further
                    x, y = o - (i - a), o + (b - i)
                    if not (a > 0 < x <= len(p) and w[a - 1] == p[x - 1]) and not (b < len(w) and y < len(p) and w[b] == p[y]):
                        continue
                lo, left = i, o
                while lo > 0 and left > 0 and w[lo - 1] == p[left - 1]:
                    lo, left = lo - 1, left - 1
                hi, right = i, o
                while hi < len(w) and right < len(p) and w[hi] == p[right]:
                    hi, right = hi + 1, right + 1
                done[n, i - o] = hi
                if hi - lo >= window:
                    out.append((lo, hi))
                    if hi > b or i >= b:
                        a, b = lo, hi
    return out


def repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """Columns _k, _r, spans: for each row with repeats, ranges [lo, hi) of words to remove. _r is xxhash64 of the text."""
    ship(docs.sparkSession)
    found = settled(lambda: _found(docs, key, text, window, gram), "ranges")
    return found.groupBy("_k", "_r").agg(F.sort_array(F.collect_list(F.struct("lo", "hi"))).alias("spans"))


def _found(docs: DataFrame, key: str, text: str, window: int, gram: int) -> DataFrame:
    """Columns _k, _r, lo, hi: the ranges of `repeats`."""
    source = docs.select(F.col(f"`{key}`").cast("long").alias("_k"), F.xxhash64(F.col(f"`{text}`")).alias("_r"), F.col(f"`{text}`").alias("_t"))
    fragments = _fragments(source, window, gram)
    passages, met = _owned(fragments, window)
    n_words = passages.agg(F.coalesce(F.sum(F.size(F.split("body", " "))), F.lit(0))).first()[0]
    shards = max(1, -(-n_words // SHARD_WORDS))
    of = lambda owner: F.pmod(F.xxhash64(owner), F.lit(shards))
    visits = stored(met.groupBy("_k", "_r", of(F.col("owner")).alias("shard")).agg(F.collect_list("owner").alias("owners")), "visits")
    salts = visits.groupBy("shard").agg(F.ceil(F.count("*") / SHARD_ROWS).cast("int").alias("salts"))
    salted = passages.withColumn("shard", of(F.col("owner"))).join(salts, "shard").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)))
    none = F.lit(None)
    left = salted.select("shard", "salt", F.lit(0).alias("kind"), F.col("owner").alias("_k"), F.lit(0).cast("long").alias("_r"), "at", "body", none.cast("array<long>").alias("owners"))
    came = visits.join(salts, "shard").withColumn("salt", F.pmod(F.xxhash64("_k", "_r"), F.col("salts")).cast("int"))
    right = fragments.join(came, ["_k", "_r"]).select("shard", "salt", F.lit(1).alias("kind"), "_k", "_r", "at", "body", "owners")
    both = left.unionByName(right).repartition(partitions(left), "shard", "salt").sortWithinPartitions("shard", "salt", "kind")
    block = window // 2

    def locate(frames):
        auto, passages, now = None, [], None
        for f in frames:
            out = []
            for shard, salt, kind, k, r, at, body, owners in zip(f["shard"], f["salt"], f["kind"], f["_k"], f["_r"], f["at"], f["body"], f["owners"]):
                if (shard, salt) != now:
                    now, passages, auto = (shard, salt), [], None
                if kind == 0:
                    passages.append((k, body.split(" ")))
                    continue
                if auto is None:
                    auto = _automaton(passages, block)
                for lo, hi in _ranges(auto, passages, k, body, set(owners.tolist()), window):
                    out.append((k, r, at + lo, at + hi))
            yield pd.DataFrame(out, columns=["_k", "_r", "lo", "hi"])

    return both.mapInPandas(locate, "_k long, _r long, lo long, hi long").distinct()


def _marked(docs: DataFrame, key: str, text: str, window: int, gram: int) -> DataFrame:
    """`docs` as a struct _row of the other columns, with _t and spans (null where nothing repeats)."""
    spans = repeats(docs, key, text, window, gram)
    others = [F.col(f"`{c}`") for c in docs.columns if c != text]
    source = docs.select(F.struct(*others, F.lit(0).alias("_fill")).alias("_row"), F.col(f"`{key}`").cast("long").alias("_k"), F.xxhash64(F.col(f"`{text}`")).alias("_r"), F.col(f"`{text}`").alias("_t"))
    # a merge join at every size: the spans grow with the corpus, so they are never broadcast
    return source.join(spans.hint("merge"), ["_k", "_r"], "left")


def _gone(n: int, spans) -> np.ndarray:
    edge = np.zeros(n + 1, dtype=np.int64)
    if spans is not None:
        for x in spans:
            edge[x["lo"]] += 1
            edge[x["hi"]] -= 1
    return np.cumsum(edge[:-1]) > 0


def summary(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """Per row: _k, n_words, n_removed, kept_sha256 (kept words joined by one space)."""

    @F.pandas_udf("n_words long, n_removed long, kept_sha256 string")
    def judged(texts: pd.Series, spans: pd.Series) -> pd.DataFrame:
        out = []
        for t, sp in zip(texts, spans):
            w = (t or "").encode("utf-8", "replace").split()
            gone = _gone(len(w), sp)
            kept = w if not gone.any() else [x for x, g in zip(w, gone.tolist()) if not g]
            out.append((len(w), int(gone.sum()), hashlib.sha256(b" ".join(kept)).hexdigest()))
        return pd.DataFrame(out, columns=["n_words", "n_removed", "kept_sha256"])

    return _marked(docs, key, text, window, gram).select("_k", judged("_t", "spans").alias("_s")).select("_k", "_s.*")


def cleaned(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """`docs` with repeated words cut out of the text; the white space of kept words stays."""

    @F.pandas_udf("string")
    def without(t: pd.Series, spans: pd.Series) -> pd.Series:
        out = []
        for x, sp in zip(t, spans):
            if x is None or sp is None or not len(sp):
                out.append(x)
                continue
            data = x.encode("utf-8", "replace")
            s, _ = word_spans(data)
            gone = _gone(len(s), sp)
            keep = np.zeros(len(gone) + 2, dtype=bool)
            keep[1:-1] = ~gone
            turn = np.flatnonzero(keep[1:] != keep[:-1])
            ends = np.append(s, len(data))
            out.append(b"".join(data[ends[i] : ends[j]] for i, j in zip(turn[::2], turn[1::2])).decode("utf-8", "replace"))
        return pd.Series(out, dtype=object)

    marked = _marked(docs, key, text, window, gram).select("_row", without("_t", "spans").alias("_clean"))
    return marked.select(*[F.col("_clean").alias(c) if c == text else F.col("_row").getField(c).alias(c) for c in docs.columns])


def op8_substrings(spark, sf_dir: str) -> DataFrame:
    return summary(table(spark, sf_dir, "documents").select("doc_id", "text")).withColumnRenamed("_k", "doc_id")


OP8_SQL = rf"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[ \t-\r]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, i, array_to_string(w[i:i + {WINDOW - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - {WINDOW - 2})) AS i FROM d)),
hit AS (SELECT doc_id, i FROM (SELECT *, min(doc_id) OVER (PARTITION BY g) AS f FROM s) WHERE f < doc_id),
gone AS (SELECT DISTINCT doc_id, i + k AS i FROM hit, (SELECT unnest(range({WINDOW})) AS k)),
word AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS i FROM d),
kept AS (SELECT doc_id, string_agg(x, ' ' ORDER BY i) AS t FROM word ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id),
ng AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(ng.n, 0)::BIGINT AS n_removed, sha256(coalesce(kept.t, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id) LEFT JOIN ng USING (doc_id)"""
