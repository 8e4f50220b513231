"""Token counts through a digest cache.

A text's digest covers its normalised content and the tokenizer's version (a digest of its file).
Digests that the cache lacks are encoded once each, whatever the number of documents that share
them, and appended; every document then gets its count from the cache by a join.

Normalised content: texts that the tokenizer provably counts alike share a digest. For a tokenizer
that lower-cases and drops white space, as its file states (`drops_space`), these are ASCII texts
without `<|` that are equal after lower-casing and squeezing white space; all others, and all texts
of any other tokenizer, stand for themselves and are encoded whole by the library.

Only one document of each missing digest carries its text through a shuffle, keyed by the document,
so a group of copies of any size is one row there; the cache side of the last join has one row per
digest, and Spark splits a skewed document side.

Defined cases: null text counts as empty (0 bytes, 0 tokens); texts are encoded whole; repeated rows
give repeated rows; an empty table gives no rows; extra columns are not read; a null key keeps its row.
"""

from __future__ import annotations

import hashlib
import json
import os
from pathlib import Path

import pandas as pd
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import ship, stored, table, work_path

CACHE_SCHEMA = "digest binary, tokenizer string, n_tokens long"


#: All white space of Unicode.
SPACES = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"


def drops_space(path: str) -> bool:
    """Whether a tokenizer file lower-cases, and cuts texts at white space and drops it.

    The first pre-tokenizer must split at white space by its type, or keep only what matches a pattern; the
    pattern is tried on every white space character, alone and inside words.
    """
    spec = json.loads(Path(path).read_text())

    def steps(part, list_name):
        return [] if part is None else [x for p in part[list_name] for x in steps(p, list_name)] if list_name in part else [part]

    normal, cuts = steps(spec.get("normalizer"), "normalizers"), steps(spec.get("pre_tokenizer"), "pretokenizers")
    lowers = any(n["type"] == "Lowercase" or n["type"] == "BertNormalizer" and n.get("lowercase") for n in normal)
    squeezes = [n["type"] == "Replace" and n.get("pattern") == {"Regex": "\\s+"} and n.get("content") == " " for n in normal]
    plain = {"Lowercase", "BertNormalizer", "NFC", "NFD", "NFKC", "NFKD", "StripAccents"}
    if not lowers or not cuts or not all(q or n["type"] in plain for q, n in zip(squeezes, normal)):
        return False
    first = cuts[0]
    if first["type"] != "Split":
        return first["type"] in {"BertPreTokenizer", "Whitespace", "WhitespaceSplit"}
    if first["behavior"] != "Removed" or not first["invert"] or "Regex" not in first["pattern"]:
        return False
    kept = regex.compile(first["pattern"]["Regex"])
    trials = [t for c in SPACES for t in (c, c * 3, f"a{c}b", f"1{c}2", f"'{c}s", f"!{c}?", f"a{c}'s{c}1")]
    return not any(set(m) & set(SPACES) for t in trials for m in kept.findall(t))


class PieceCounter:
    """Counts of whole texts from library counts of their pieces between spaces.

    Where the tokenizer drops white space and never joins across it (`drops_space`), a text's count is
    the sum over its pieces; any other tokenizer gets whole texts. Piece counts are kept in two bounded generations.
    """

    def __init__(self, path: str, keep: int = 400_000):
        self.pieces = drops_space(path)
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.keep, self.new, self.old = keep, {}, {}
        # characters for which cutting at a space could matter: combining marks and other scripts
        self.plain = regex.compile(r"[\x00-\x1b\x20-\x7f¡-ɏ‐-‧‰-⁞₠-₿\s]*").fullmatch

    def counts(self, texts: list[str]) -> list[int]:
        plain = [self.pieces and self.plain(t) is not None for t in texts]
        split = [t.split(" ") if p else () for t, p in zip(texts, plain)]
        missing: set[str] = set()
        new, old = self.new, self.old
        for pieces in split:
            for s in set(pieces):
                if s not in new:
                    n = old.get(s)
                    if n is None:
                        missing.add(s)
                    else:
                        new[s] = n
        if missing:
            todo = list(missing)
            for s, e in zip(todo, self.tok.encode_batch_fast(todo, add_special_tokens=False)):
                new[s] = len(e)
        out = []
        for t, p, pieces in zip(texts, plain, split):
            out.append(sum(map(new.__getitem__, pieces)) if p else len(self.tok.encode(t, add_special_tokens=False)))
        if len(new) >= self.keep:
            self.old, self.new = new, {}
        return out


_LOADED: dict[str, PieceCounter] = {}


def _counter(path: str) -> PieceCounter:
    if path not in _LOADED:
        _LOADED[path] = PieceCounter(path)
    return _LOADED[path]


def tokenizer_version(path: str) -> str:
    return hashlib.sha256(Path(path).read_bytes()).hexdigest()[:32]


def normalised(text: Column) -> Column:
    """Equal only for texts that a lower-casing tokenizer without white space counts alike."""
    ascii_only = (F.octet_length(text) == F.length(text)) & ~text.contains("<|")
    folded = F.trim(F.regexp_replace(F.lower(text), r"[ \t\n\r]+", " "))
    return F.when(ascii_only, folded).otherwise(text)


def digest(text: Column, folds: bool = True) -> Column:
    """`folds`: whether texts that a lower-casing tokenizer without white space counts alike may share it."""
    return F.unhex(F.sha2(F.encode(normalised(text) if folds else text, "UTF-8"), 256))


def count_tokens(docs: DataFrame, path: str, cache: str | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row of `docs`: key, n_bytes, n_tokens. `cache` is the path of the count table.

    The cache is a Parquet table of CACHE_SCHEMA on shared storage; it is made if absent and grows
    by the digests that this call encodes. Without a path a fresh one in the working folder is used.
    """
    spark = docs.sparkSession
    ship(spark)
    version, folds = tokenizer_version(path), drops_space(path)
    cache = cache or work_path(spark, "token-cache")
    body = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    keyed = stored(docs.select(F.col(f"`{key}`").alias("_k"), F.octet_length(body).cast("long").alias("n_bytes"), digest(body, folds).alias("digest")), "token-digests")
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    at = jvm.org.apache.hadoop.fs.Path(cache)
    exists = at.getFileSystem(conf).exists(at)
    read = lambda: spark.read.schema(CACHE_SCHEMA).parquet(cache).where(F.col("tokenizer") == version)
    first = keyed.groupBy("digest").agg(F.min("_k").alias("_k"))
    if exists:
        first = first.join(read().select("digest"), "digest", "left_anti")
    # the row that stands for a digest brings its text; null keys cannot join and are encoded apart
    source = docs.select(F.col(f"`{key}`").alias("_k"), body.alias("_text"))
    misses = source.join(first.where("_k is not null"), "_k").where(digest(F.col("_text"), folds) == F.col("digest")).select("digest", "_text")
    lost = first.where("_k is null").select("digest")
    bare = source.where("_k is null").select(digest(F.col("_text"), folds).alias("digest"), "_text").join(lost, "digest", "left_semi")

    def run(frames):
        counter = _counter(path)
        for f in frames:
            f = f.drop_duplicates("digest")
            yield pd.DataFrame({"digest": f["digest"], "tokenizer": version, "n_tokens": counter.counts(list(f["_text"]))})

    misses.unionByName(bare).mapInPandas(run, CACHE_SCHEMA).dropDuplicates(["digest"]).write.mode("append").parquet(cache)
    # written before the join, so that both its sides are plain exchanges and a hot digest can be split
    counts = stored(read().groupBy("digest").agg(F.min("n_tokens").alias("n_tokens")), "token-counts")
    return keyed.join(counts, "digest").select(F.col("_k").alias(key), "n_bytes", "n_tokens")


def op1_token_counts(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers as tokenizers

    counted = count_tokens(table(spark, sf_dir, "documents").select("doc_id", "text"), tokenizers.path("word_bpe_49k.json"))
    return counted.withColumn("over_limit", F.col("n_tokens") > 2048)
