"""Near-dedup keeps little on disk: shuffle files go with the step that made them, unlike texts that meet are not verified."""

import random
import time

from foldstar.llm import shared
from foldstar.llm import similar as S
from tests.llm.test_similar import brute


def shuffle_files(spark):
    found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {found.apply(i).getName() for i in range(found.size()) if found.apply(i).getName().startswith("shuffle")}


def test_a_stored_table_leaves_no_shuffle_files(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(shared, "shared_dir", lambda _: str(tmp_path))
    had = shuffle_files(spark)
    df = shared.stored(spark.range(20_000).selectExpr("id % 1009 AS k").groupBy("k").count(), "counts")
    for _ in range(100):
        if not (left := shuffle_files(spark) - had):
            break
        time.sleep(0.1)
    assert not left and df.count() == 1009
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"


def test_texts_that_share_a_passage_are_not_verified(spark, monkeypatch):
    """A passage of 45 words in texts of 100 others, and two copies of one of them but for a word."""
    r = random.Random(2)
    passage = [f"p{i}" for i in range(45)]
    docs = {i: " ".join([f"w{r.randrange(10**6)}" for _ in range(50)] + passage + [f"w{r.randrange(10**6)}" for _ in range(50)]) for i in range(40)}
    docs |= {100: docs[7] + " x", 101: "y " + docs[7]}
    tried, plain = [], S.verified

    def counted(pairs, nodes, threshold):
        tried.append(pairs.distinct().count())
        return plain(pairs, nodes, threshold)

    monkeypatch.setattr(S, "verified", counted)
    monkeypatch.setattr(S, "BUCKETS", 16)  # so few that common shingles are not told from rare ones
    monkeypatch.setattr(S, "SLICE", 4, raising=False)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    assert {r["_k"]: r["component_id"] for r in S.near_duplicates(df).collect()} == brute(docs)
    assert sum(tried) <= 6


def test_sketches_rule_out_no_similar_pair(spark):
    r = random.Random(9)
    rows, want, pairs = [], set(), []
    for i in range(0, 400, 2):
        n = r.choice([1, 9, 50, 400, 3000])
        a = {r.getrandbits(63) for _ in range(n)}
        b = set(list(a)[: n - r.randint(0, n // 4)]) | {r.getrandbits(63) for _ in range(r.randint(0, n // 6))}
        if len(a & b) >= 0.8 * len(a | b):
            want.add((i, i + 1))
        pairs.append((i, i + 1))
        rows += [(i + k, len(x), S._sketch(S.np.array(sorted(x), dtype=S.np.int64)).tolist()) for k, x in ((0, a), (1, b))]
    sketches = spark.createDataFrame(rows, "node long, n int, bits array<long>")
    got = {tuple(x) for x in S.sieved(spark.createDataFrame(pairs, "a long, b long"), sketches, 0.8).collect()}
    assert want <= got and len(got) < len(pairs)
