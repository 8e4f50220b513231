"""Best-fit packing by length patterns and non-negative least squares.

Documents become pieces of at most `size` tokens. The histogram of piece lengths has at most `size`
entries, whatever the corpus, so planning runs on the driver on bounded data:

1. Patterns: all sets of up to `depth` lengths that fill a sequence exactly (lengths that occur).
2. Repeat counts: non-negative least squares of pattern counts against the histogram, by projected
   gradient with momentum on the sparse pattern matrix.
3. Rounding down, never beyond what the histogram holds.
4. Residuals: best fit, longest first, on counts of equal open sequences.

The plan is a list of (lengths, how often). The r-th piece of a length takes that length's r-th slot.
Ranks come from counts per (length, bucket of keys) and a running number inside each bucket, so no
length, however common, meets in one task, and a task that is run again gives the same ranks. Pieces
of full length are sequences of their own (numbers below zero) and skip the plan.

Defined cases: a null or empty text is the end token alone; texts are encoded whole; rows with equal
keys are packed one by one; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import base64
import os
import zlib
from collections import defaultdict

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from foldstar.llm.shared import ship, stored, table

SIZE = 1024
END = 2
DEPTH = 3
BUCKET_ROWS = 20_000

PIECES = "piece int, start long, length long, ids_crc32 long"


class Ids:
    """Token ids by the tokenizers library; plain texts by the same vocabulary's rank table.

    For texts of Latin letters, digits and common marks without special strings, the rank table
    gives the library's ids (tested) several times faster; all others go to the library.
    """

    def __init__(self, path: str, ranks: str | None, pattern: str | None):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.fast = None
        self.plain = regex.compile(r"[\t\n\r\x20-\x7e¡-ɏ‐-‧‰-⁞₠-₿]*").fullmatch
        if ranks:
            import tiktoken

            with open(ranks, "rb") as f:
                table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=table, special_tokens={})

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is not None and "<|" not in text and self.plain(text):
            return np.array(self.fast.encode_ordinary(text), dtype="<u4")
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, dtype="<u4")


_LOADED: dict[tuple, Ids] = {}


def _ids(*key) -> Ids:
    if key not in _LOADED:
        _LOADED[key] = Ids(*key)
    return _LOADED[key]


def pieces(docs: DataFrame, path: str, ranks: str | None = None, pattern: str | None = None, size: int = SIZE, end: int = END, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Columns _k, piece, start, length, ids_crc32: every document cut into pieces, the first the shorter one."""
    ship(docs.sparkSession)

    @F.pandas_udf(f"array<struct<{', '.join(x.replace(' ', ':') for x in PIECES.split(', '))}>>")
    def cut(texts: pd.Series) -> pd.Series:
        encode = _ids(path, ranks, pattern)
        out = []
        for t in texts:
            ids = np.append(encode(t or ""), np.uint32(end)).astype("<u4")
            n = len(ids)
            first = n % size or size
            edges = [0, *range(first, n + 1, size)]
            out.append([{"piece": i, "start": a, "length": b - a, "ids_crc32": zlib.crc32(ids[a:b].tobytes())} for i, (a, b) in enumerate(zip(edges, edges[1:]))])
        return pd.Series(out)

    return docs.select(F.col(f"`{key}`").alias("_k"), F.explode(cut(F.col(f"`{text}`"))).alias("_p")).select("_k", "_p.*")


def patterns(lengths: list[int], size: int, depth: int = DEPTH) -> np.ndarray:
    """Rows of `depth` indices into `lengths` (padded by -1) whose lengths add up to `size`."""
    at = {n: i for i, n in enumerate(lengths)}
    rows = []
    if size in at:
        rows.append((at[size],))
    for i, a in enumerate(lengths):
        if 2 * a <= size and size - a in at:
            rows.append((i, at[size - a]))
    if depth >= 3:
        for i, a in enumerate(lengths):
            if 3 * a > size:
                break
            for j in range(i, len(lengths)):
                c = size - a - lengths[j]
                if c < lengths[j]:
                    break
                if c in at:
                    rows.append((i, j, at[c]))
    out = np.full((len(rows), max(depth, 1)), -1)
    for r, row in enumerate(rows):
        out[r, : len(row)] = row
    return out


def fit(pats: np.ndarray, hist: np.ndarray, rounds: int = 400) -> np.ndarray:
    """Counts x >= 0 that nearly minimise |A x - hist|, A the pattern matrix; short lengths weigh less."""
    if not len(pats):
        return np.zeros(0)
    n = len(hist)
    weight = np.linspace(0.5, 1.0, n)
    pad = np.append(weight, 0.0)
    use = pad[pats]  # index -1 meets the padding

    def apply(x):
        return np.bincount(pats.ravel() % (n + 1), (use * x[:, None]).ravel(), minlength=n + 1)[:n]

    def back(r):
        return (use * np.append(r, 0.0)[pats]).sum(axis=1)

    v = np.ones(len(pats))
    for _ in range(20):
        v = back(apply(v))
        top = np.linalg.norm(v)
        v /= top
    goal = weight * hist
    x = y = np.zeros(len(pats))
    t = 1.0
    for _ in range(rounds):
        nxt = np.maximum(y - back(apply(y) - goal) / top, 0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = nxt + (t - 1) / t2 * (nxt - x)
        x, t = nxt, t2
    return x


def plan(hist: dict[int, int], size: int = SIZE, depth: int = DEPTH) -> list[tuple[tuple[int, ...], int]]:
    """(lengths, count) of sequences that hold every piece of the histogram exactly once."""
    left = {n: c for n, c in hist.items() if c > 0}
    out: dict[tuple[int, ...], int] = defaultdict(int)
    lengths = sorted(left)
    pats = patterns(lengths, size, depth)
    x = fit(pats, np.array([left[n] for n in lengths], dtype=float))
    for r in np.argsort(-x, kind="stable"):
        row = [lengths[i] for i in pats[r] if i >= 0]
        need = {n: row.count(n) for n in row}
        k = min([int(x[r])] + [left[n] // c for n, c in need.items()])
        if k > 0:
            out[tuple(sorted(row, reverse=True))] += k
            for n, c in need.items():
                left[n] -= k * c
    # residuals: open sequences are counted by what they hold, best fit by what they have left
    space: dict[int, dict[tuple[int, ...], int]] = defaultdict(dict)
    for n in sorted(left, reverse=True):
        todo = left[n]
        while todo:
            room = min((s for s in space if s >= n and space[s]), default=None)
            if room is None:
                fits = size // n
                full, rest = divmod(todo, fits)
                for held, k in (((n,) * fits, full), ((n,) * rest, 1 if rest else 0)):
                    if k:
                        s = size - sum(held)
                        space[s][held] = space[s].get(held, 0) + k
                break
            held, k = next(iter(space[room].items()))
            fits = room // n
            used = min(k, max(1, todo // fits)) if todo >= fits else 1
            take = min(fits, todo)
            if used == k:
                del space[room][held]
            else:
                space[room][held] = k - used
            grown = held + (n,) * take
            s = size - sum(grown)
            space[s][grown] = space[s].get(grown, 0) + used
            todo -= used * take
    for group in space.values():
        for held, k in group.items():
            out[held] += k
    return sorted(out.items())


def slots(plan_rows) -> tuple[np.ndarray, ...]:
    """Arrays sorted by (length, first rank): length, first rank, first sequence, offset."""
    taken: dict[int, int] = defaultdict(int)
    rows, sequence = [], 0
    for held, k in plan_rows:
        offset = 0
        for n in held:
            rows.append((n, taken[n], sequence, offset))
            taken[n] += k
            offset += n
        sequence += k
    rows.sort()
    return tuple(np.array(c, dtype=np.int64) for c in zip(*rows)) if rows else (np.zeros(0, dtype=np.int64),) * 4


def pack(docs: DataFrame, path: str, ranks: str | None = None, pattern: str | None = None, size: int = SIZE, end: int = END, depth: int = DEPTH, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per piece: _k, piece, start, length, ids_crc32, sequence_id, offset."""
    made = stored(pieces(docs, path, ranks, pattern, size, end, key, text), "pieces")
    columns = ["_k", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    # a full piece is a sequence of its own and needs no rank
    whole = made.where(F.col("length") == size).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    cut = made.where(F.col("length") < size)
    n = cut.count()
    buckets = max(1, -(-n // BUCKET_ROWS))
    keyed = cut.withColumn("b", F.pmod(F.xxhash64("_k", "piece", "start"), F.lit(buckets)).cast("int"))
    counts = keyed.groupBy("length", "b").agg(F.count("*").alias("n"))
    counts = stored(counts, "lengths")
    hist = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `size` rows
    length, first, sequence, offset = slots(plan(hist, size, depth))
    scale = np.int64(1) << 44
    edge = length * scale + first

    @F.pandas_udf("sequence_id long, offset long")
    def place(lengths: pd.Series, rank: pd.Series) -> pd.DataFrame:
        n, r = lengths.to_numpy(), rank.to_numpy()
        at = np.searchsorted(edge, n * scale + r, side="right") - 1
        return pd.DataFrame({"sequence_id": sequence[at] + r - first[at], "offset": offset[at]})

    base = counts.withColumn("base", F.sum("n").over(Window.partitionBy("length").orderBy("b").rowsBetween(Window.unboundedPreceding, -1))).select("length", "b", F.coalesce("base", F.lit(0)).alias("base"))
    inside = Window.partitionBy("length", "b").orderBy("_k", "piece", "start", "ids_crc32")
    ranked = keyed.withColumn("r", F.row_number().over(inside) - 1).join(base, ["length", "b"])
    placed = ranked.select("_k", "piece", "start", "length", "ids_crc32", place("length", F.col("base") + F.col("r")).alias("_s")).select("_k", "piece", "start", "length", "ids_crc32", "_s.*")
    return whole.select(*columns).unionByName(placed.select(*columns))


def packed_text(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """Pieces of `documents` with the byte-level vocabulary, packed: the last stage of the pipeline."""
    import public_tokenizers as tokenizers

    made = pack(docs, tokenizers.path("byte_bpe_50k.json"), tokenizers.path("byte_bpe_50k.tiktoken"), tokenizers.PATTERN, size)
    return made.withColumnRenamed("_k", "doc_id")


def op7_packing(spark, sf_dir: str) -> DataFrame:
    return packed_text(table(spark, sf_dir, "documents").select("doc_id", "text"))
