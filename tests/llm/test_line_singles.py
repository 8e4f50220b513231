import random

from foldstar.llm import lines as L

SF = "/root/testdata/sf0.001"


def brute(docs, words):
    """Later copies of two-line runs and of single lines of `words` words or more, by place."""
    runs, seen, left = set(), set(), {}
    for k in sorted(docs):
        full = docs[k].split("\n")
        at = [i for i, x in enumerate(full) if x.split()]
        dead = set()
        for a, b in zip(at, at[1:]):
            if (full[a], full[b]) in runs:
                dead |= {a, b}
            runs.add((full[a], full[b]))
        for i in at:
            if full[i] in seen and len(full[i].split()) >= words:
                dead.add(i)
            seen.add(full[i])
        left[k] = (len(at), len(dead), "\n".join(x for i, x in enumerate(full) if i not in dead))
    return left


def test_single_repeated_line_goes(spark):
    rows = [(1, "one line of five words\nx"), (2, "y\none line of five words\nz"), (3, "short line\nu"), (4, "v\nshort line")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in L.deduped(df, single_words=5).collect()}
    assert got == {1: rows[0][1], 2: "y\nz", 3: rows[2][1], 4: rows[3][1]}
    assert {r["doc_id"]: r["text"] for r in L.deduped(df, single_words=None).collect()} == dict(rows)


def test_random(spark):
    r = random.Random(7)
    docs = {i: "\n".join(r.choice(["a", "b c", "d e f", " g\th  i ", "", "j k l m"]) for _ in range(r.randint(0, 8))) for i in range(80)}
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    want = brute(docs, 3)
    got = {x["doc_id"]: (x["n_lines"], x["n_removed"]) for x in L.summary(df, single_words=3).collect()}
    assert got == {k: v[:2] for k, v in want.items()}
    assert {x["doc_id"]: x["text"] for x in L.deduped(df, single_words=3).collect()} == {k: t for k, (a, b, t) in want.items() if b == 0 or b < a}


def test_query(spark):
    less = L.summary(spark.read.parquet(f"{SF}/documents.parquet"), single_words=None).agg({"n_removed": "sum"}).first()[0]
    assert L.op4_line_dedup(spark, SF).agg({"n_removed": "sum"}).first()[0] > less
