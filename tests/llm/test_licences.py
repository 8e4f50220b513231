import random

from foldstar.llm import licences as S

SF = "/root/testdata/sf0.001"


def brute(text, threshold=0.8):
    """Every unit against every template, without bounds."""
    if not text:
        return None, 0.0, 0
    lines = text.split("\n")
    best, n = None, 0

    def top(u):
        a = S.bigrams(S.words_of(u))
        found = []
        for i, (_, t) in enumerate(S.TEMPLATES):
            b = S.bigrams(S.words_of(t))
            d = 2 * len(a & b) / (len(a) + len(b))
            if d >= threshold:
                found.append((-d, -len(b), i))
        return min(found, default=None)

    paragraphs, held = [], []
    for x in lines + [""]:
        if x.strip():
            held.append(x)
        elif held:
            paragraphs.append("\n".join(held))
            held = []
    for u in lines:
        n += top(u) is not None
    best = min((t for t in map(top, [*lines, *paragraphs, text]) if t), default=None)
    return (None, 0.0, n) if best is None else (S.TEMPLATES[best[2]][0], -best[0], n)


def test_query(spark):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    got = {r["doc_id"]: (r["licence"], r["dice"], r["n_lines"]) for r in S.op10_licences(spark, SF).collect()}
    assert got == {k: brute(t) for k, t in docs.items()}
    assert sum(v[0] is not None for v in got.values()) > 0
    for k, t in docs.items():
        assert ("Licensed under CC BY-NC 4.0." in t.split("\n")) <= (got[k][0] is not None)


def test_pruning_loses_nothing():
    r = random.Random(3)
    scanner = S.Scanner()
    vocabulary = [w for _, t in S.TEMPLATES for w in t.split()]
    for _ in range(600):
        lines = []
        for _ in range(r.randint(1, 4)):
            w = r.choice(S.TEMPLATES)[1].split()
            for _ in range(r.randint(0, len(w) // 4)):
                w[r.randrange(len(w))] = r.choice(vocabulary)
            cut = r.randint(0, len(w))
            lines += r.choice([[" ".join(w)], [" ".join(w[:cut]), " ".join(w[cut:])], [""], ["x y"]])
        t = "\n".join(lines)
        assert scanner.text(t) == brute(t), t


def test_defined_cases(spark):
    texts = [None, "", "MIT", "released UNDER the mit license", "word " * 20000, "a\n\nReleased under the\nMIT License.\n\nb"]
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)] + [(3, texts[3], 1)], "doc_id long, text string, dice int")
    got = sorted(map(tuple, S.scan(df).collect()), key=str)
    assert got == sorted(((i, *brute(t)) for i, t in [*enumerate(texts), (3, texts[3])]), key=str)
    assert got[3][1] == "MIT" and S.scan(df.limit(0)).count() == 0
