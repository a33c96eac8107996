"""Compare a query with its DuckDB SQL on the given tables."""

import os

import duckdb

ROOT = "/root/testdata"


def sql_rows(sql, sf="sf0.001", **tables):
    con = duckdb.connect()
    con.execute("SET timezone='UTC'")
    for name in os.listdir(f"{ROOT}/{sf}"):
        path = f"{ROOT}/{sf}/{name}" + ("/*.parquet" if os.path.isdir(f"{ROOT}/{sf}/{name}") else "")
        con.execute(f"CREATE VIEW {name.split('.')[0]} AS SELECT * FROM '{path}'")
    for name, frame in tables.items():
        con.register(f"given_{name}", frame)
        con.execute(f"CREATE OR REPLACE VIEW {name} AS SELECT * FROM given_{name}")
    result = con.execute(sql)
    names = [d[0] for d in result.description]
    order = sorted(range(len(names)), key=names.__getitem__)
    return sorted(names), sorted((tuple(row[i] for i in order) for row in result.fetchall()), key=repr)


def spark_rows(df):
    names = sorted(df.columns)
    return names, sorted((tuple(row[n] for n in names) for row in df.collect()), key=repr)
