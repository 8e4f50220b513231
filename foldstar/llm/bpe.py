"""Byte-level BPE encoding and decoding with a queue of merge ranks kept in a hierarchical bitmap.

Every merge rank has a bucket of places (left ends of adjacent symbol pairs in a linked list). A
bitmap marks the buckets that hold places; two summary levels above it make "lowest rank present"
three find-first-set steps, whatever the length of the pre-tokens. Places whose pair has changed
since they were queued are recognised by their rank and skipped. One queue serves many pre-tokens at
once: they lie end to end in the list, no pair crosses from one to the next, and a bucket is emptied
from left to right until a merge makes a pair of the same or a lower rank, which then comes first. So
each pre-token sees its pairs by rank, then from the left. Work is O(n log n) in the bytes.

Results of short pieces of text are kept in two bounded generations of a dictionary per worker.

Defined cases: a null or empty text has no tokens (digests of the empty string); special strings are
ordinary text; texts are taken whole, a single pre-token of millions of bytes included; repeated
rows give repeated rows; extra columns are not read.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import ship, table


#: Pre-tokens that share a queue: enough to fill buckets, few enough to stay in the processor's cache.
TOGETHER = 1000


class ByteBPE:
    """Encoder and decoder for a table of ranks (token bytes to rank)."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, keep: int = 800_000):
        self.ranks, self.keep = ranks, keep
        self.tokens = {v: k for k, v in ranks.items()}
        self.decimal = [b"%d" % i for i in range(max(self.tokens) + 1)].__getitem__
        self.split = regex.compile(pattern).findall
        self.byte_pairs = np.full(1 << 16, -1, dtype=np.int64)
        for k, v in ranks.items():
            if len(k) == 2:
                self.byte_pairs[k[0] << 8 | k[1]] = v
        # the queue: places by rank, and which ranks have any, in three levels
        words = (max(ranks.values()) >> 6) + 1
        self.buckets: dict[int, list[int]] = {}
        self.leaf, self.mid = [0] * words, [0] * ((words >> 6) + 1)
        self.uneven = regex.compile(r"\s\s|^\s|\s$").search
        self.cut = regex.compile(r"(?<=\S)(?= \S)").split
        self.tails: dict[str, tuple[bytes, bytes]] = {}
        self.new: dict[str, tuple[bytes, bytes]] = {}
        self.old: dict[str, tuple[bytes, bytes]] = {}

    @classmethod
    def from_file(cls, path: str, pattern: str) -> ByteBPE:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, pattern)

    def _push(self, r: int, p: int, top: int) -> int:
        """Open a bucket for rank r; returns the top level of the bitmap."""
        self.buckets[r] = [p]
        i = r >> 6
        word = self.leaf[i]
        self.leaf[i] = word | 1 << (r & 63)
        if not word:
            self.mid[i >> 6] |= 1 << (i & 63)
            top |= 1 << (i >> 6)
        return top

    def merge_many(self, pieces: list[bytes]) -> list[list[int]]:
        """Token ids of many pre-tokens."""
        ranks, buckets, leaf, mid, push = self.ranks, self.buckets, self.leaf, self.mid, self._push
        get = ranks.get
        text = b"".join(pieces)
        n = len(text)
        # symbol at place p spans text[p:after[p]]; before[p] is the place to its left; edge: a pre-token starts
        after, before = list(range(1, n + 2)), list(range(-1, n))
        edge = bytearray(n + 1)
        at = 0
        for x in pieces:
            edge[at] = 1
            at += len(x)
        edge[n] = 1
        # ranks of all byte pairs at once; a bucket for each rank that occurs
        raw = np.frombuffer(text, dtype=np.uint8).astype(np.intp)
        found = np.full(n, -1, dtype=np.int64)
        found[:-1] = self.byte_pairs[raw[:-1] << 8 | raw[1:]]
        found[np.flatnonzero(np.frombuffer(edge, dtype=np.uint8)[1:])] = -1
        pair = found.tolist()  # rank of the pair at a place, as last queued
        order = np.argsort(found, kind="stable")
        order = order[np.searchsorted(found[order], 0) :]
        by_rank = found[order]
        cuts = np.flatnonzero(by_rank[1:] != by_rank[:-1]) + 1
        places = order.tolist()
        top, start = 0, 0
        for cut in [*cuts.tolist(), len(places)] if places else ():
            r = pair[places[start]]
            top = push(r, 0, top)
            buckets[r] = places[start:cut]
            start = cut
        while top:
            # find first set, level by level: the lowest rank that has places
            j = (top & -top).bit_length() - 1
            word = mid[j]
            i = (j << 6) + (word & -word).bit_length() - 1
            word = leaf[i]
            low = word & -word
            r = (i << 6) + low.bit_length() - 1
            word ^= low
            leaf[i] = word
            if not word:
                mid[j] ^= 1 << (i & 63)
                if not mid[j]:
                    top ^= 1 << j
            places = buckets.pop(r)
            if len(places) > 1:
                places.sort()
            sooner = False
            for k, p in enumerate(places):
                if pair[p] != r:
                    continue  # stale: the pair here has changed
                m = after[p]
                end = after[m]
                after[p] = end
                pair[m] = -1
                if edge[end]:
                    pair[p] = -1
                else:
                    before[end] = p
                    pair[p] = s = get(text[p : after[end]], -1)
                    if s >= 0:
                        if s in buckets:
                            buckets[s].append(p)
                        else:
                            top = push(s, p, top)
                        sooner = s <= r
                if not edge[p]:
                    left = before[p]
                    s = get(text[left:end], -1)
                    if s >= 0 and pair[left] != s:
                        if s in buckets:
                            buckets[s].append(left)
                        else:
                            top = push(s, left, top)
                        sooner = sooner or s <= r
                    pair[left] = s
                if sooner:
                    for p in places[k + 1 :]:
                        if r in buckets:
                            buckets[r].append(p)
                        else:
                            top = push(r, p, top)
                    break
        out, p = [], 0
        for x in pieces:
            stop = p + len(x)
            ids = []
            while p < stop:
                e = after[p]
                ids.append(ranks[text[p:e]])
                p = e
            out.append(ids)
        return out

    def merge(self, piece: bytes) -> list[int]:
        return self.merge_many([piece])[0]

    def encode(self, text: str) -> list[int]:
        return [i for ids in self.merge_many([x.encode("utf-8", "replace") for x in self.split(text)]) for i in ids]

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))

    def _known(self, pre: str) -> tuple[bytes, bytes] | None:
        if pre[0] == " ":
            return self.new.get(pre[1:]) or self.old.get(pre[1:])
        return self.tails.get(pre)

    def _fill(self, words: set[str], firsts: set[str]) -> tuple[dict, dict]:
        """Decimal ids joined by commas and decoded bytes: of a space and each word, and of pre-tokens without a space."""
        fill, split, wanted = {}, {}, set()
        for w in words:
            got = self.old.get(w)
            if got is not None:
                fill[w] = got
                continue
            split[w] = pre = self.split(" " + w)
            wanted.update(pre)
        wanted |= firsts
        made = {}
        todo = []
        for x in wanted:
            got = self._known(x)
            if got is None:
                todo.append(x)
            else:
                made[x] = got
        decimal = self.decimal
        for k in range(0, len(todo), TOGETHER):
            some = todo[k : k + TOGETHER]
            for x, ids in zip(some, self.merge_many([x.encode("utf-8", "replace") for x in some])):
                made[x] = (b",".join(map(decimal, ids)), self.decode(ids))
        for w, pre in split.items():
            if len(pre) == 1:
                fill[w] = made[pre[0]]
            else:
                parts = [made[x] for x in pre]
                fill[w] = b",".join([a for a, _ in parts]), b"".join([b for _, b in parts])
        return fill, made

    def digests(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """Per text: number of tokens, SHA-256 of the decimal ids joined by commas, SHA-256 of the decoded bytes."""
        held, words, firsts, get = [], set(), set(), self.new.get
        for text in texts:
            # cut at single spaces between two non-spaces: no pre-token reaches across such a place
            if not text:
                held.append(None)
                continue
            if self.uneven(text) is None:
                pieces = text.split(" ")
                first = pieces.pop(0)
            else:
                first, *pieces = self.cut(text)
                pieces = [p[1:] for p in pieces]
            found = list(map(get, pieces))
            if None in found:
                words.update([p for p, g in zip(pieces, found) if g is None])
            else:
                pieces = None
            first = self.split(first)
            firsts.update(first)
            held.append((first, pieces, found))
        fill, made = self._fill(words, firsts)
        self.new.update(fill)
        out = []
        for h in held:
            if h is None:
                empty = hashlib.sha256(b"").hexdigest()
                out.append((0, empty, empty))
                continue
            first, pieces, found = h
            if pieces is not None:
                found = list(map(get, pieces))
            found[:0] = [made[x] for x in first]
            numbers, spans = zip(*found)
            ids = b",".join(numbers)
            out.append((ids.count(b",") + 1, hashlib.sha256(ids).hexdigest(), hashlib.sha256(b"".join(spans)).hexdigest()))
        self._keep(fill, made)
        return out

    def _keep(self, fill: dict, made: dict) -> None:
        if len(self.tails) >= self.keep:
            self.tails.clear()
        self.tails.update((x, v) for x, v in made.items() if len(x) <= 64 and x[0] != " ")
        new = self.new
        for w in [w for w in fill if len(w) > 64]:
            del new[w]
        if len(new) >= self.keep:
            self.old, self.new = new, {}
        new = self.new
        for x, v in made.items():
            if len(x) <= 64 and x[0] == " ":
                new[x[1:]] = v

    def digest(self, text: str) -> tuple[int, str, str]:
        return self.digests([text])[0]


_LOADED: dict[tuple[str, str], ByteBPE] = {}


def loaded(path: str, pattern: str) -> ByteBPE:
    """One encoder for each rank file in a worker process."""
    if (path, pattern) not in _LOADED:
        _LOADED[path, pattern] = ByteBPE.from_file(path, pattern)
    return _LOADED[path, pattern]


def round_trip(docs: DataFrame, path: str, pattern: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: key, n_tokens, ids_sha256, decoded_sha256. One scan, no shuffle."""
    ship(docs.sparkSession)

    @F.pandas_udf("n_tokens long, ids_sha256 string, decoded_sha256 string")
    def digests(texts: pd.Series) -> pd.DataFrame:
        bpe = loaded(path, pattern)
        return pd.DataFrame(bpe.digests([t or "" for t in texts]), columns=["n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(f"`{key}`"), digests(F.col(f"`{text}`")).alias("_d")).select(F.col(f"`{key}`"), "_d.*")


def encoded(docs: DataFrame, path: str, pattern: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: key and the array of token ids."""
    ship(docs.sparkSession)

    def run(frames):
        bpe = loaded(path, pattern)
        for f in frames:
            yield pd.DataFrame({key: f[key], "ids": [bpe.encode(t or "") for t in f[text]]})

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(key, text).mapInPandas(run, f"`{key}` {kind}, ids array<int>")


def decoded(df: DataFrame, path: str, pattern: str, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """Per row: key and the decoded text (bytes that are no UTF-8 become U+FFFD)."""
    ship(df.sparkSession)

    def run(frames):
        bpe = loaded(path, pattern)
        for f in frames:
            yield pd.DataFrame({key: f[key], "text": [None if x is None else bpe.decode(int(i) for i in x).decode("utf-8", "replace") for x in f[ids]]})

    kind = df.schema[key].dataType.simpleString()
    return df.select(key, ids).mapInPandas(run, f"`{key}` {kind}, text string")


def op9_byte_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers as tokenizers

    return round_trip(table(spark, sf_dir, "documents"), tokenizers.path("byte_bpe_multi_50k.tiktoken"), tokenizers.PATTERN)
