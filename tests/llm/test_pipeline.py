import corpus_pipeline as C
from foldstar.llm.shared import stored
from foldstar.llm.lines import SINGLE_WORDS
from tests.llm.test_line_singles import brute as lines_brute
from tests.llm.test_packing import check
from tests.llm.test_similar import brute as similar_brute
from tests.llm.test_substrings import brute as substring_brute

SF = "/root/testdata/sf0.001"


def as_dict(df):
    return {r["doc_id"]: r["text"] for r in df.collect()}


def test_stages_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    stages = dict(C.STAGES)
    good = stored(stages["quality rules"](spark, docs, SF), "test")
    assert good.columns == docs.columns
    texts = as_dict(good)
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    assert not [k for k in texts if labels.get(k) == 0]
    before = as_dict(docs)
    clean = [k for k, q in labels.items() if q == 1 and len(before[k].split()) >= 60]
    assert sum(k in texts for k in clean) >= 0.98 * len(clean)
    kept = stored(stages["line dedup"](spark, good, SF), "test")
    assert kept.columns == docs.columns
    texts2 = as_dict(kept)
    assert texts2 == {k: t for k, (a, b, t) in lines_brute(texts, SINGLE_WORDS).items() if b == 0 or b < a}
    assert all(r["n_chars"] == len(r["text"]) for r in kept.collect())
    near = stored(stages["near-dedup"](spark, kept, SF), "test")
    assert near.columns == docs.columns
    root = similar_brute(texts2)
    texts3 = as_dict(near)
    assert texts3 == {k: t for k, t in texts2.items() if root[k] == k}
    cut = stored(stages["substring dedup"](spark, near, SF), "test")
    assert cut.columns == docs.columns
    import hashlib

    want = {k: h for k, n, g, h in substring_brute(sorted(texts3.items())) if n > g}
    texts4 = as_dict(cut)
    assert {k: hashlib.sha256(" ".join(t.split()).encode()).hexdigest() for k, t in texts4.items()} == want
    packed = stored(stages["packing"](spark, cut, SF), "test")
    check([(r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"], r["sequence_id"], r["offset"]) for r in packed.collect()], texts4)
    assert C.run(spark, SF).count() == packed.count()


def test_empty_and_null(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([(1, None, None, None, None), (None, "", "en", "s", 0), (2, "x " * 70, "en", "s", 140)], docs.schema)
    for some in (docs.limit(0), odd):
        for _, stage in C.STAGES:
            some = stored(stage(spark, some, SF), "test")
