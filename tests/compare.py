"""A query against its SQL: rows as multisets, columns by name, doubles to six digits."""

import glob
import os

import duckdb


def normal(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])

    def value(x):
        if isinstance(x, float):
            return round(x, 6)
        if isinstance(x, (list, tuple)):
            return tuple(map(value, x))
        return round(float(x), 6) if hasattr(x, "as_tuple") else x

    return sorted((tuple(value(r[i]) for i in order) for r in rows), key=repr), sorted(columns)


def by_sql(sql, sf_dir):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from read_parquet('{f}')")
    got = con.execute(sql)
    return normal(got.fetchall(), [c[0] for c in got.description])


def same(df, sql, sf_dir):
    return normal([tuple(r) for r in df.collect()], df.columns) == by_sql(sql, sf_dir)
