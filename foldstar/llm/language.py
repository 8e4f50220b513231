"""Language identification: sparse multinomial logistic regression on TF-IDF of character n-grams.

Features are hashed character n-grams (orders 1 to `top`) of the lower-cased text, weighted by
log(1 + count) times inverse document frequency and scaled to unit length. Document frequencies are
counted over all rows to learn from. The weights are trained with the follow-the-regularised-leader
update with an L1 and an L2 penalty, on a sample of at most `sample_rows` labelled rows; every fifth
of them is kept back, and one temperature is fitted on those by minimum log loss.

Learning sees only text and label of rows for which crc32(key as text) mod 4 is not 2; predictions
see only the text.

Defined cases: null texts and texts without a letter are `und` with score 1; texts are taken whole;
ties between labels go to the first in sorted order; repeated rows are predicted alike; with no
labelled row every text is `und` with score 0; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import ship, table

TOP = 3
BUCKETS = 1 << 14
SAMPLE_ROWS = 3_000
HELD_OUT_REST = 2

_LETTER = regex.compile(r"\p{L}").search
_PIECE = 1 << 20


@dataclass
class Model:
    labels: list[str]
    idf: np.ndarray
    weights: np.ndarray  # buckets x labels
    bias: np.ndarray
    temperature: float = 1.0
    zero_share: float = field(default=0.0)

    def scores(self, counts: np.ndarray) -> np.ndarray:
        at = np.flatnonzero(counts)
        x = np.log1p(counts[at]) * self.idf[at]
        norm = np.linalg.norm(x)
        z = self.bias + (x / norm if norm else x) @ self.weights[at]
        z = z / self.temperature
        z = np.exp(z - z.max())
        return z / z.sum()


def gram_counts(text: str, top: int = TOP, buckets: int = BUCKETS) -> np.ndarray:
    """Counts of the hashed character n-grams of a whole text."""
    low = text.lower()
    out = np.zeros(buckets, dtype=np.int64)
    for s in range(0, max(len(low), 1), _PIECE):
        part = low[max(0, s - top + 1) : s + _PIECE] if s else low[:_PIECE]
        c = np.frombuffer(part.encode("utf-32-le", "replace"), dtype=np.uint32)
        h = np.zeros(len(c), dtype=np.uint32)
        for n in range(1, top + 1):
            if len(c) < n:
                break
            h = (h[: len(c) - n + 1] * np.uint32(0x01000193)) ^ c[n - 1 :] * np.uint32(0x9E3779B1)
            mixed = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
            skip = top - n if s else 0  # the overlap's shorter grams were counted before
            got = np.bincount(((mixed >> np.uint32(12)) & np.uint32(buckets - 1))[skip:], minlength=buckets)
            out += got
    return out


def to_learn(docs: DataFrame, key: str, text: str, label: str) -> DataFrame:
    fold = F.crc32(F.col(f"`{key}`").cast("string").cast("binary")) % 4
    return docs.where(F.coalesce(fold != HELD_OUT_REST, F.lit(False)) & F.col(f"`{label}`").isNotNull() & F.col(f"`{text}`").isNotNull()).select(
        F.col(f"`{key}`").cast("string").alias("_k"), F.col(f"`{text}`").alias("_t"), F.col(f"`{label}`").cast("string").alias("_y")
    )


def document_frequency(learn: DataFrame, buckets: int = BUCKETS, top: int = TOP) -> tuple[int, np.ndarray]:
    """How many of all rows to learn from have each bucket; a row of sums for each task goes through one group-by."""

    def run(frames):
        n, df = 0, np.zeros(buckets, dtype=np.int64)
        for f in frames:
            for t in f["_t"]:
                df += gram_counts(t, top, buckets) > 0
            n += len(f)
        yield pd.DataFrame({"i": np.append(np.arange(buckets), -1), "n": np.append(df, n)})

    got = learn.select("_t").mapInPandas(run, "i int, n long").groupBy("i").agg(F.sum("n").alias("n")).toPandas()  # buckets + 1 rows
    df = np.zeros(buckets + 1, dtype=np.int64)
    df[got["i"]] = got["n"]
    return int(df[-1]), df[:-1]


def sample(learn: DataFrame, rows: int, buckets: int = BUCKETS, top: int = TOP) -> list:
    """A fixed sample of at most `rows` labelled rows as sparse counts, the same on every run."""

    @F.pandas_udf("i array<int>, n array<int>")
    def sparse(t: pd.Series) -> pd.DataFrame:
        found = [gram_counts(x, top, buckets) for x in t]
        return pd.DataFrame({"i": [np.flatnonzero(c) for c in found], "n": [c[c > 0] for c in found]})

    order = F.xxhash64("_k", F.lit(17))
    picked = learn.select(order.alias("o"), "_k").orderBy("o", "_k").limit(rows)
    return learn.join(F.broadcast(picked), "_k", "left_semi").select("_k", "_y", sparse("_t").alias("c")).orderBy(F.xxhash64("_k", F.lit(17)), "_k").limit(rows).collect()


def train(rows: list, n: int, df: np.ndarray, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.0005, l2: float = 0.01, passes: int = 3) -> Model:
    """Follow-the-regularised-leader with per-coordinate rates and elastic-net penalties, then the temperature."""
    labels = sorted({r["_y"] for r in rows})
    at = {y: i for i, y in enumerate(labels)}
    idf = np.log((1 + n) / (1 + df)) + 1
    size, k = len(df), len(labels)
    z, g2 = np.zeros((size + 1, k)), np.zeros((size + 1, k))

    def solve(zi, gi):
        w = -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(gi)) / alpha + l2)
        return np.where(np.abs(zi) > l1, w, 0.0)

    def features(r):
        i = np.asarray(r["c"]["i"], dtype=np.int64)
        x = np.log1p(np.asarray(r["c"]["n"])) * idf[i]
        norm = np.linalg.norm(x)
        return np.append(i, size), np.append(x / norm if norm else x, 1.0)

    ready = [(*features(r), at[r["_y"]]) for r in rows]
    fit = [r for j, r in enumerate(ready) if j % 5] or ready
    back = [r for j, r in enumerate(ready) if j % 5 == 0]
    for _ in range(passes):
        for i, x, y in fit:
            w = solve(z[i], g2[i])
            p = x @ w
            p = np.exp(p - p.max())
            p /= p.sum()
            p[y] -= 1
            g = x[:, None] * p
            more = g2[i] + g * g
            z[i] += g - (np.sqrt(more) - np.sqrt(g2[i])) / alpha * w
            g2[i] = more
    w = solve(z, g2)
    model = Model(labels, idf, w[:-1], w[-1], 1.0, float((w[:-1] == 0).mean()))
    if back:
        logits = np.array([x @ w[i] for i, x, _ in back])
        y = np.array([y for *_, y in back])

        def loss(t):
            s = logits / t
            s = s - s.max(axis=1, keepdims=True)
            return float((np.log(np.exp(s).sum(axis=1)) - s[np.arange(len(y)), y]).mean())

        grid = np.exp(np.linspace(np.log(0.05), np.log(20), 121))
        model.temperature = float(min(grid, key=loss))
    return model


def learn_model(docs: DataFrame, key: str = "doc_id", text: str = "text", label: str = "lang", sample_rows: int = SAMPLE_ROWS) -> Model | None:
    ship(docs.sparkSession)
    learn = to_learn(docs, key, text, label)
    n, df = document_frequency(learn)
    rows = sample(learn, sample_rows) if n else []
    return train(rows, n, df) if rows else None


def predict(docs: DataFrame, model: Model | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: key, held_out, lang_pred, score."""
    ship(docs.sparkSession)

    @F.pandas_udf("lang_pred string, score double")
    def judged(texts: pd.Series) -> pd.DataFrame:
        out = []
        for t in texts:
            if t is None or _LETTER(t) is None:
                out.append(("und", 1.0))
            elif model is None:
                out.append(("und", 0.0))
            else:
                p = model.scores(gram_counts(t))
                best = int(p.argmax())
                out.append((model.labels[best], float(p[best])))
        return pd.DataFrame(out, columns=["lang_pred", "score"])

    fold = F.coalesce(F.crc32(F.col(f"`{key}`").cast("string").cast("binary")) % 4 == HELD_OUT_REST, F.lit(False))
    return docs.select(F.col(f"`{key}`"), fold.alias("held_out"), judged(F.col(f"`{text}`")).alias("_p")).select(F.col(f"`{key}`"), "held_out", "_p.*")


def op2_language(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return predict(docs, learn_model(docs))
