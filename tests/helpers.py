import glob
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows(df):
    return sorted(map(repr, (tuple(r) for r in df.collect())))


def oracle(sql, sf_dir, columns):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.sql(f"create view {t} as select * from '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    out = con.sql(sql)
    at = [out.columns.index(c) for c in columns]
    return sorted(map(repr, (tuple(r[i] for i in at) for r in out.fetchall())))


def same(spark, query, sql, sf_dir):
    df = query(spark, sf_dir)
    assert rows(df) == oracle(sql, sf_dir, df.columns)


def union_find(vertices, edges):
    up = {v: v for v in vertices}

    def find(x):
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {v: find(v) for v in up}
