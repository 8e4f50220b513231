"""Run a registered query and its SQL side by side, order-insensitively."""

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def sql_rows(sql: str, sf_dir: str):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    rel = con.sql(sql)
    cols = sorted(rel.columns)
    return cols, rel.select(*[duckdb.ColumnExpression(c) for c in cols]).fetchall()


def norm(rows):
    def cell(x):
        if isinstance(x, float):
            return repr(x + 0.0)
        return repr(x)

    return sorted(tuple(cell(x) for x in r) for r in rows)


def assert_same(df, sql: str, sf_dir: str):
    cols = sorted(df.columns)
    got = norm([tuple(r) for r in df.select(*[f"`{c}`" for c in cols]).collect()])
    want_cols, want = sql_rows(sql, sf_dir)
    assert cols == want_cols
    want = norm(want)
    assert len(got) == len(want)
    bad = [(a, b) for a, b in zip(got, want) if a != b]
    assert not bad, (len(bad), bad[:3])
