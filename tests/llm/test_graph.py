import random

from foldstar.llm.graph import components


def test_rounds_and_one_task_agree(spark):
    r = random.Random(8)
    pairs = [(i, i + 1) for i in range(100, 160)] + [(500, 500 + i) for i in range(1, 40)]
    pairs += [(r.randrange(1000, 1400), r.randrange(1000, 1400)) for _ in range(180)] + [(-5, 7), (7, -5), (3, 3)]
    root = {n: n for p in pairs for n in p if p[0] != p[1]}
    for a, b in pairs:
        if a != b:
            x, y = sorted((root[a], root[b]))
            root = {n: x if v == y else v for n, v in root.items()}
    r.shuffle(pairs)
    df = spark.createDataFrame(pairs + [(None, 1)], "a long, b long")
    for few in (0, 50, 1 << 20):
        got = components(df, few).collect()
        assert len(got) == len(root)
        assert {x["node"]: x["root"] for x in got} == root
    assert components(df.limit(0)).collect() == []
