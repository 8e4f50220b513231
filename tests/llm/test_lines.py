import random

import pytest

from foldstar.llm import lines as L
from tests.compare import assert_same

SF = "/root/testdata/sf0.001"


def test_query_matches_sql(spark):
    assert_same(L.op4_line_dedup(spark, SF), L.OP4_SQL, SF)


def brute(docs, m):
    seen, gone = set(), {}
    for k in sorted(docs):
        full = (docs[k] or "").split("\n")
        at = [i for i, x in enumerate(full) if x.strip(" \t\n\r\x0b\x0c")]
        dead = set()
        for n in range(len(at) - m + 1):
            g = tuple(full[i] for i in at[n : n + m])
            if g in seen:
                dead.update(at[n : n + m])
            seen.add(g)
        gone[k] = (len(at), len(dead), None if docs[k] is None else "\n".join(x for i, x in enumerate(full) if i not in dead))
    return gone


@pytest.mark.parametrize("m", [1, 2, 5])
def test_random(spark, m):
    import hashlib

    r = random.Random(m)
    docs = {i: "\n".join(r.choice(["a", "b", "c", "", " ", "d e"]) for _ in range(r.randint(0, 14))) for i in range(60)}
    docs |= {100: None, 101: "", 102: "\n\n", 103: "x\n" * (3000 if m == 2 else 40), 104: docs[5]}
    df = spark.createDataFrame([(k, t, "clash") for k, t in docs.items()], "doc_id long, text string, n string")
    want = brute(docs, m)
    got = {r["doc_id"]: (r["n_lines"], r["n_removed"], r["kept_sha256"]) for r in L.summary(df, min_lines=m, single_words=None).collect()}
    assert got == {k: (a, b, None if t is None else hashlib.sha256(t.encode()).hexdigest()) for k, (a, b, t) in want.items()}
    kept = L.deduped(df, min_lines=m, single_words=None)
    assert kept.columns == df.columns
    assert {r["doc_id"]: r["text"] for r in kept.collect()} == {k: t for k, (a, b, t) in want.items() if b == 0 or b < a}


def test_repeated_and_keyless_rows(spark):
    rows = [(1, "a\nb"), (1, "a\nb"), (None, "a\nb"), (1, "a\nb\nc"), (2, "a\nb")]
    got = sorted((tuple(r)[:3] for r in L.summary(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert sum(g[2] for g in got if g[0] == 1) in (2, 4) and (2, 2, 2) in got and (None, 2, 0) in got
    assert L.summary(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def sorted_suffixes(docs):
    """Every suffix as (lines, key, place), in order: a suffix that ends comes before longer ones."""
    rank = {}
    out = []
    for k, t in docs.items():
        x = [y for y in t.split("\n") if y.strip()]
        out += [(x[n:], k, n) for n in range(len(x))]
    return out


def common(a, b):
    n = 0
    while n < min(len(a), len(b)) and a[n] == b[n]:
        n += 1
    return n


def some_docs(seed, letters="abc", most=14):
    r = random.Random(seed)
    docs = {i: "\n".join(r.choice(letters) for _ in range(r.randint(1, most))) for i in range(25)}
    return docs | {50: docs[3], 51: docs[3] + "\n" + docs[4], 52: "x\n" * 70, 53: "y\n" + "x\n" * 41 + "z"}


@pytest.mark.parametrize("seed", [1, 2])
def test_suffix_order_and_prefixes(spark, seed):
    docs = some_docs(seed)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    lines = L.suffixes(df, "doc_id", "text")
    order = L.ranks(lines)
    # line IDs follow the digests, so the brute force sorts by them
    name = {x: (r["d1"], r["d2"]) for x, r in ((docs[r["_k"]].split("\n")[r["i"]], r) for r in lines.collect())}
    every = [([name[y] for y in x], k, n) for x, k, n in sorted_suffixes(docs)]
    want = {(k, n): sum(o < x for o, _, _ in every) for x, k, n in every}
    assert {(r["_k"], r["n"]): r["rank"] for r in order.collect()} == want
    array = L.prefixes(order).collect()
    array.sort(key=lambda r: (r["rank"], r["_k"], r["_r"], r["n"]))
    text = {(k, n): x for x, k, n in every}
    first = [x[0] for x, _, _ in every]
    assert len(array) == sum(first.count(x) > 1 for x in first)
    for a, b in zip(array, array[1:]):
        assert b["lcp"] == common(text[a["_k"], a["n"]], text[b["_k"], b["n"]])
    assert array[0]["lcp"] == 0


def test_maximal_runs(spark):
    docs = some_docs(5, "abcdefgh")
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    every = sorted_suffixes(docs)
    longest = {(k, n): max(common(x, o) for o, q, m in every if (q, m) != (k, n)) for x, k, n in every}
    rows = {(k, n): x[: longest[k, n]] for x, k, n in every if longest[k, n] >= 2}
    want = sorted((k, n, len(x), sum(y == x for y in rows.values())) for (k, n), x in rows.items() if longest.get((k, n - 1), 0) <= len(x))
    got = L.runs(df).collect()
    assert sorted((r["_k"], r["i"], r["length"], r["copies"]) for r in got) == want
    by = {}
    for r in got:
        by.setdefault(r["run"], set()).add(tuple(rows[r["_k"], r["i"]]))
    assert all(len(x) == 1 for x in by.values())


def test_two_digests_are_two():
    """A second digest made from the first alone would add nothing."""
    import inspect

    assert 'F.xxhash64(F.lit(1), "s.x")' in inspect.getsource(L.suffixes)
