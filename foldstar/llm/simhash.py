"""SimHash near-duplicates by pigeonhole blocks.

Fingerprints within `distance` bits agree on all but `distance` of any set of blocks, so close pairs
share the value of some `blocks - distance` blocks. Distinct fingerprints (a group of exact copies
is one of them) are keyed by each such choice of blocks; keys that one fingerprint alone has drop
out, the rest are verified by Hamming distance in bounded groups. A group emits a spanning forest of
its links, never all its pairs; components follow by rounds of stars.

A key with more than `group_limit` fingerprints is keyed anew by narrower choices that leave 12 bits
free, so at most 4096 distinct fingerprints can share one: exact, linear in the group's size and
bounded for every task, whatever share of all rows one group holds.

Defined cases: a null or empty text has fingerprint zero and links like any other; fewer than three
words are one shingle; texts are taken whole; repeated rows share a fingerprint and a component; a
row with a null key gets its fingerprint, and its component is the smallest key that is not null
(null if there is none); extra columns are not read.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.graph import Forest, components, groups
from foldstar.llm.shared import partitions, ship, stored, table

SEED = 42
_LANES = sum((((np.arange(256, dtype=np.uint64) >> np.uint64(b)) & np.uint64(1)) << np.uint64(8 * b)) for b in range(8))
_BIT = np.uint64(1) << np.arange(64, dtype=np.uint64)
_CHUNK = 1 << 18


def hashes(text: str | None, shingle: int) -> np.ndarray:
    """64-bit hashes of a text's word shingles, repeats included; no word: none."""
    w = (text or "").encode("utf-8", "replace").lower().split()
    if not w:
        return np.empty(0, dtype=np.uint64)
    joined = b" ".join(w)
    if len(w) <= shingle:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], dtype=np.uint64)
    ends = np.cumsum(np.fromiter(map(len, w), dtype=np.int64, count=len(w)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    digest = xxhash.xxh64_intdigest
    n = len(w) - shingle + 1
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends[shingle - 1 :].tolist())), dtype=np.uint64, count=n)


def bits(h: np.ndarray) -> int:
    """Signed 64-bit fingerprint: the bits set in over half of the hashes (none: zero)."""
    if not len(h):
        return 0
    ones = np.zeros(64, dtype=np.int64)
    for s in range(0, len(h), _CHUNK):
        lanes = _LANES[h[s : s + _CHUNK].view(np.uint8).reshape(-1, 8)]
        # 255 rows at most fit the eight 8-bit lanes of a word
        sums = np.add.reduceat(lanes, np.arange(0, len(lanes), 255), axis=0)
        ones += sums.view(np.uint8).reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int((_BIT[2 * ones > len(h)]).sum(dtype=np.uint64).astype(np.int64))


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Signed 64-bit SimHash of a text's word shingles, repeats included."""
    return bits(hashes(text, shingle))


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 3) -> DataFrame:
    """Columns _k (the key) and fp (long)."""
    ship(docs.sparkSession)

    @F.pandas_udf("long")
    def prints(texts: pd.Series) -> pd.Series:
        return pd.Series(np.fromiter((fingerprint(t, shingle) for t in texts), dtype=np.int64, count=len(texts)))

    return docs.select(F.col(f"`{key}`").alias("_k"), prints(F.col(f"`{text}`")).alias("fp"))


def masks(blocks: int, distance: int) -> list[int]:
    """Bit masks (signed) of every choice of blocks - distance blocks of 64 bits."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    block = [((1 << hi) - 1) ^ ((1 << lo) - 1) for lo, hi in zip(edges, edges[1:])]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    return [signed(sum(c)) for c in combinations(block, blocks - distance)]


def _keyed(fps: DataFrame, wanted: list[int]) -> DataFrame:
    choice = F.posexplode(F.array(*[F.lit(m).cast("long") for m in wanted])).alias("c", "m")
    return fps.select("fp", choice).select("fp", "c", F.col("fp").bitwiseAND(F.col("m")).alias("k"))


def _linked(distance: int):
    def run(frames):
        for g in groups(frames, ["c", "k"]):
            f = g["fp"].to_numpy()
            u = f.view(np.uint64)
            forest = Forest(len(u))
            step = max(1, (1 << 19) // len(u))
            for s in range(0, len(u), step):
                i, j = np.nonzero(np.bitwise_count(u[s : s + step, None] ^ u[None, :]) <= distance)
                forest.add(i + s, j)
            child = np.flatnonzero(forest.up != np.arange(len(u)))
            if len(child):
                yield pd.DataFrame({"a": f[child], "b": f[forest.up[child]]})

    return run


def links(fps: DataFrame, distance: int = 3, blocks: int = 5, group_limit: int = 2048) -> DataFrame:
    """Edges a, b between distinct fingerprints (column fp): a forest with the components of all links."""

    def verified(keyed: DataFrame) -> DataFrame:
        dealt = keyed.repartition(partitions(keyed), "c", "k").sortWithinPartitions("c", "k")
        return dealt.mapInPandas(_linked(distance), "a long, b long")

    def shared_keys(keyed: DataFrame) -> DataFrame:
        n = keyed.groupBy("c", "k").agg(F.count("*").alias("n")).where("n > 1")
        return keyed.join(n, ["c", "k"])

    first = stored(shared_keys(_keyed(fps, masks(blocks, distance))), "simhash-keys")
    found = verified(first.where(F.col("n") <= group_limit))
    large = first.where(F.col("n") > group_limit).select("fp").distinct()
    # 16 blocks of 4 bits: a key leaves 4 * distance bits free
    narrow = shared_keys(_keyed(large, masks(16, distance)))
    return found.unionByName(verified(narrow))


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", distance: int = 3, blocks: int = 5, group_limit: int = 2048, shingle: int = 3) -> DataFrame:
    """Per row: _k, fp, component_id (smallest key reachable by links)."""
    own = stored(fingerprints(docs, key, text, shingle), "simhash")
    classes = stored(own.groupBy("fp").agg(F.min("_k").alias("rep")), "simhash-classes")
    roots = components(links(classes.select("fp"), distance, blocks, group_limit))
    placed = classes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    named = placed.groupBy("root").agg(F.min("rep").alias("component_id"))
    by_fp = placed.select("fp", "root").join(named, "root").select("fp", "component_id")
    return own.join(by_fp, "fp").select("_k", "fp", "component_id")


def keep_first(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """The rows of `docs` whose key is their component's smallest; rows with a null key stay."""
    kept = near_duplicates(docs, key, text, **how).where("_k = component_id").select(F.col("_k").alias(key)).distinct()
    return docs.where(F.col(f"`{key}`").isNotNull()).join(kept, key, "left_semi").select(*[F.col(f"`{c}`") for c in docs.columns]).unionByName(docs.where(F.col(f"`{key}`").isNull()))


def op6_simhash(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select(F.col("_k").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
