import random

from foldstar.llm import licences as S


def brute(text, threshold=0.8):
    """Every run of words against every template."""
    w = S.words_of(text)
    found = []
    for i, (_, t) in enumerate(S.TEMPLATES):
        b = S.bigrams(S.words_of(t))
        for p in range(len(w)):
            for q in range(p + 2, len(w) + 1):
                a = S.bigrams(w[p:q])
                d = 2 * len(a & b) / (len(a) + len(b))
                if d >= threshold:
                    found.append((-d, -len(b), i))
    best = min(found, default=None)
    return None if best is None else (-best[0], best[2])


def test_windows_against_all_runs():
    r = random.Random(11)
    scanner = S.Scanner()
    short = [t for _, t in S.TEMPLATES if len(t.split()) < 14]
    for _ in range(40):
        w = " ".join(r.choice(short) for _ in range(2)).split()
        for _ in range(r.randint(0, 4)):
            w[r.randrange(len(w))] = r.choice(["x", "the", "License", "under"])
        text = " ".join(["some", "words"] * r.randint(0, 2) + w + ["and", "more"])
        assert scanner.window(text) == brute(text), text


def test_notice_beside_other_text(spark):
    gpl = S.TEMPLATES[6][1].split()
    header = "/*\n * Tool, copyright A. Person\n *\n * " + " ".join(gpl[:14]) + "\n * " + " ".join(gpl[14:]) + "\n *\n * It comes without any warranty; see the files beside this one for all further details, and write to the people named there with any other question about its use.\n */"
    prose = "We say here for all our readers that " + S.TEMPLATES[5][1] + " See the file beside this one."
    df = spark.createDataFrame([(1, header), (2, prose), (3, "no notice")], "doc_id long, text string")
    assert sorted(map(tuple, S.scan(df).collect())) == [(1, "GPL-3.0", 1.0, 0), (2, "GPL-3.0", 1.0, 0), (3, None, 0.0, 0)]
    assert S.Scanner().text(header)[0] is None and S.Scanner().text(prose)[0] is None
