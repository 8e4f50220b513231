"""Near-duplicates by the Jaccard similarity of sets of word shingles: SimHash blocks first, then an exact way for the rest.

Pigeonhole blocks (simhash.links) find the sets whose fingerprints differ in few bits; a pair of similarity
0.8 differs in about ten bits of 64 and is mostly out of their reach. For the rest: two sets of similarity t
share at least t of the larger one, so in any common order of all shingles their first n - ceil(t n) + 1
members meet. The order here is by the count of a shingle's bucket (one of BUCKETS, counted over all texts),
then by the hash, so that common shingles come last; only those first members cross a shuffle. Where h is the
first member that two sets have in common, nothing before it counts, so what each set has from h on bounds
their overlap; a meeting in h that this bound rules out is no candidate, and a similar pair always stays one
where its first common member is. A set's sketch is PARITY bits, each the parity of its members in one cell of
the hashes: the bits in which two sketches differ are no more than the members that only one set has, so a pair
with more of them than a similar pair can have goes without a look at the sets. Every other candidate is verified
on the whole sets, which are made again from the texts of these pairs alone; texts meet the wanted keys where they
are, without a shuffle, unless there are more than FEW_KEYS of these.

A group (the texts that meet in one shingle) never emits all its pairs. In a group of more than `group`
texts each is first tried against the text whose shingles meet the most others, which near copies share;
afterwards only texts outside the group's largest component are tried, against texts of other components.
So a group of near copies costs its size, and no link between components is lost. The cost of a large group
of texts that meet but are not alike remains their number outside that component times the group.

Equal sets are one node. Defined cases: fewer than `shingle` words are one shingle; texts without a word have
the empty set and are copies of each other; repeated rows share a node; ties of group leaders go to the
larger node; rows with a null key stay and have no component; an empty table gives no rows; extra columns pass through.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm import simhash
from foldstar.llm.graph import components
from foldstar.llm.shared import filtered, released, settled, ship, stored, table

THRESHOLD, SHINGLE, GROUP = 0.8, 5, 64
BUCKETS, SLICE = 1 << 20, 1 << 12
PARITY = 1024
FEW_KEYS = 1 << 19


def _set(text: str | None, shingle: int) -> np.ndarray:
    return np.unique(simhash.hashes(text, shingle).view(np.int64))


def _digest(s: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(s.tobytes())).astype(np.int64))


def _sketch(s: np.ndarray) -> np.ndarray:
    """Parities of the members in each of PARITY cells of the hashes, as longs."""
    return np.packbits(np.bincount(s.view(np.uint64) >> np.uint64(54), minlength=PARITY) & 1).view(np.int64)


def bucket_counts(docs: DataFrame, text: str, shingle: int) -> np.ndarray:
    """How many distinct shingles of all texts fall in each bucket of hashes; BUCKETS numbers come to the driver."""

    def run(frames):
        total = np.zeros(BUCKETS, dtype=np.int64)
        for f in frames:
            for t in f["t"]:
                s, c = np.unique(_set(t, shingle) & (BUCKETS - 1), return_counts=True)
                total[s] += c
        if total.any():
            yield pd.DataFrame({"b": np.arange(0, BUCKETS, SLICE), "c": list(total.reshape(-1, SLICE))})

    def added(frames):
        for f in frames:
            yield pd.DataFrame({"b": f["b"], "c": [np.sum([np.asarray(x) for x in parts], axis=0) for parts in f["parts"]]})

    ship(docs.sparkSession)
    # a few tasks a core: each sends an array of all buckets, whatever it has read
    some = docs.select(F.col(f"`{text}`").alias("t")).coalesce(8 * docs.sparkSession.sparkContext.defaultParallelism)
    found = some.mapInPandas(run, "b long, c array<long>").groupBy("b").agg(F.collect_list("c").alias("parts")).mapInPandas(added, "b long, c array<long>").toPandas()
    counts = np.zeros(BUCKETS, dtype=np.int32)
    for b, c in zip(found["b"], found["c"]):
        counts[b : b + SLICE] = np.minimum(c, np.iinfo(np.int32).max)
    return counts


def signatures(docs: DataFrame, key: str, text: str, threshold: float, shingle: int) -> DataFrame:
    """Columns _k, node (a digest of the set), fp (its SimHash), n (its size), x (its first members, of which similar sets share one), bits (its sketch)."""
    counts = bucket_counts(docs, text, shingle)

    @F.pandas_udf("node long, fp long, n int, x array<long>, bits array<long>")
    def signed(texts: pd.Series) -> pd.DataFrame:
        rows = []
        for t in texts:
            s = _set(t, shingle)
            take = len(s) - int(np.ceil(threshold * len(s) - 1e-9)) + 1 if len(s) else 0
            rows.append((_digest(s), simhash.bits(s.view(np.uint64)), len(s), s[np.lexsort((s, counts[s & (BUCKETS - 1)]))[:take]], _sketch(s)))
        return pd.DataFrame(rows, columns=["node", "fp", "n", "x", "bits"])

    return docs.select(F.col(f"`{key}`").alias("_k"), signed(F.col(f"`{text}`")).alias("y")).select("_k", "y.*")


def shingle_sets(docs: DataFrame, key: str, text: str, shingle: int, wanted: DataFrame) -> DataFrame:
    """Columns node, s (sorted distinct shingle hashes) of the nodes in `wanted` (node, rep: a key of it)."""
    ship(docs.sparkSession)

    @F.pandas_udf("own long, s array<long>")
    def sets(texts: pd.Series) -> pd.DataFrame:
        found = [_set(t, shingle) for t in texts]
        return pd.DataFrame({"own": [_digest(s) for s in found], "s": found})

    wanted = stored(wanted, "wanted-keys")
    met = docs.select(F.col(f"`{key}`").alias("rep"), F.col(f"`{text}`").alias("_t")).join(F.broadcast(wanted) if wanted.count() <= FEW_KEYS else wanted, "rep")
    made = filtered(met.select("node", sets("_t").alias("y")), F.expr("node = y.own"))  # a plain filter makes sets of all texts below the join
    return made.select("node", "y.s").dropDuplicates(["node"])


def _pairs(a, b) -> list:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def sieved(pairs: DataFrame, sketches: DataFrame, threshold: float) -> DataFrame:
    """The distinct pairs a, b of nodes that their sketches (node, n, bits) do not rule out: every pair of similarity `threshold` or more stays."""
    x, y = sketches.toDF("a", "na", "xa"), sketches.toDF("b", "nb", "xb")
    differ = F.aggregate(F.zip_with("xa", "xb", lambda u, v: F.bit_count(u.bitwiseXOR(v))), F.lit(0), lambda u, v: u + v)
    most = (F.col("na") + F.col("nb")) * ((1 - threshold) / (1 + threshold)) + 1e-6
    return pairs.distinct().join(x, "a").join(y, "b").where(differ <= most).select("a", "b")


def verified(pairs: DataFrame, sets_of, threshold: float) -> DataFrame:
    """The distinct pairs a, b of nodes with similarity `threshold` or more; `sets_of` gives node and s for a table of nodes."""
    pairs = stored(pairs.distinct(), "candidate-pairs")
    nodes = stored(sets_of(pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()), "shingle-sets")
    sets = pairs.join(nodes.select(F.col("node").alias("a"), F.col("s").alias("sa")), "a").join(nodes.select(F.col("node").alias("b"), F.col("s").alias("sb")), "b")
    common = F.size(F.array_intersect("sa", "sb"))
    return sets.where(common * (1 + threshold) >= (F.size("sa") + F.size("sb")) * threshold - 1e-9).select("a", "b")


def by_fingerprint(nodes: DataFrame) -> DataFrame:
    """Candidate pairs a, b of nodes: a star in each fingerprint, and SimHash links between the stars."""
    heads = stored(nodes.groupBy("fp").agg(F.min("node").alias("head")), "fingerprint-heads")
    same = nodes.join(heads, "fp").where("node <> head").select(*_pairs("node", "head"))
    near = simhash.links(heads.select("fp")).distinct()
    ends = near.join(heads.toDF("a", "ha"), "a").join(heads.toDF("b", "hb"), "b").select(*_pairs("ha", "hb"))
    return same.unionByName(ends)


def prefixes(nodes: DataFrame) -> DataFrame:
    """Columns node, n, h, rest, c: the first members h of each node that c > 1 nodes have among theirs, with the count of its members from h on."""
    spread = nodes.select("node", "n", F.posexplode("x").alias("at", "h")).withColumn("rest", F.col("n") - F.col("at")).drop("at")
    shared = spread.groupBy("h").agg(F.count("*").alias("c")).where("c > 1")
    return stored(spread.join(shared, "h").select("node", "n", "h", "rest", "c"), "shingle-prefixes")


def _placed(first: DataFrame, edges: DataFrame) -> DataFrame:
    """`first` with the component of each node as `root`."""
    return first.join(components(edges), "node", "left").withColumn("root", F.coalesce("root", "node"))


def _met(a: DataFrame, b: DataFrame, threshold: float) -> DataFrame:
    """Pairs of nodes in different components that share a shingle h and may be similar with h as their first common member."""
    cols = ["h", "node", "n", "rest", "root"]
    x, y = a.select(cols).toDF("h", "a", "na", "sa", "ra"), b.select(cols).toDF("h", "b", "nb", "sb", "rb")
    like = F.least("na", "nb") >= F.greatest("na", "nb") * threshold - 1e-9
    enough = F.least("sa", "sb") * (1 + threshold) >= (F.col("na") + F.col("nb")) * threshold - 1e-9
    return x.join(y, "h").where(like & enough & (F.col("ra") != F.col("rb"))).select(*_pairs("a", "b"))


def links(nodes: DataFrame, sets_of, threshold: float = THRESHOLD, group: int = GROUP) -> DataFrame:
    """Edges a, b between nodes (columns node, fp, n, x, bits) of similarity `threshold` or more, with the components of all such pairs.

    `sets_of` gives node and s for a table of nodes. A table of nodes that `stored` returned is deleted once it is read.
    """
    close, first = stored(by_fingerprint(nodes), "fingerprint-pairs"), prefixes(nodes)
    sketches = stored(nodes.select("node", "n", "bits"), "sketches")
    released(nodes)
    tried = lambda pairs: verified(sieved(pairs, sketches, threshold), sets_of, threshold)
    edges = settled(lambda: tried(close), "close-pairs")
    # the leader of a large group is the node whose first members meet the most
    scores = first.groupBy("node").agg((F.sum("c") / F.first("n")).alias("score"))
    large = _placed(first.where(F.col("c") > group), edges)
    leaders = large.join(scores, "node").groupBy("h").agg(F.max(F.struct("score", "node", "n", "rest", "root")).alias("l")).select("h", "l.*")
    more = settled(lambda: tried(_met(large, leaders, threshold)), "close-pairs")
    edges = edges.unionByName(more)
    placed = stored(_placed(first, edges).drop("c"), "placed-prefixes")
    released(first)
    sizes = placed.groupBy("h", "root").agg(F.count("*").alias("c"))
    largest = sizes.groupBy("h").agg(F.count("*").alias("parts"), F.max(F.struct("c", "root"))["root"].alias("main")).where("parts > 1").drop("parts")
    apart = placed.join(largest, "h").where("root <> main")
    return edges.unionByName(settled(lambda: tried(_met(apart, placed, threshold)), "close-pairs"))


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD, shingle: int = SHINGLE, group: int = GROUP) -> DataFrame:
    """Per row: _k, component_id (smallest key reachable by links; null for a null key)."""
    keyed = docs.where(F.col(f"`{key}`").isNotNull())
    signed = stored(signatures(keyed, key, text, threshold, shingle), "signatures")
    classes = stored(signed.groupBy("node").agg(F.min("_k").alias("rep"), *[F.first(c).alias(c) for c in ("fp", "n", "x", "bits")]), "shingle-classes")
    own = stored(signed.select("_k", "node"), "row-nodes")
    released(signed)
    reps = stored(classes.select("node", "rep"), "node-keys")

    def sets_of(nodes):
        return shingle_sets(keyed, key, text, shingle, reps.join(nodes, "node"))

    roots = components(links(classes, sets_of, threshold, group))
    placed = reps.join(roots, "node", "left").select("node", "rep", F.coalesce("root", "node").alias("root"))
    named = placed.groupBy("root").agg(F.min("rep").alias("component_id"))
    found = own.select("_k", "node").join(placed.join(named, "root").select("node", "component_id"), "node").select("_k", "component_id")
    rest = docs.where(F.col(f"`{key}`").isNull()).select(F.col(f"`{key}`").alias("_k"), F.col(f"`{key}`").alias("component_id"))
    return found.unionByName(rest)


def keep_first(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """The rows of `docs` whose key is their component's smallest; rows with a null key stay."""
    keyed = docs.where(F.col(f"`{key}`").isNotNull())
    kept = settled(lambda: near_duplicates(keyed, key, text, **how).where("_k = component_id").select(F.col("_k").alias(key)).distinct(), "kept-keys")
    return keyed.join(kept, key, "left_semi").select(*[F.col(f"`{c}`") for c in docs.columns]).unionByName(docs.where(F.col(f"`{key}`").isNull()))


def op6_similar(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select(F.col("_k").alias("doc_id"), "component_id")
