"""A query's rows beside those of its SQL in DuckDB."""

from __future__ import annotations

import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def same(con: duckdb.DuckDBPyConnection, frame, sql: str) -> None:
    con.register("got", frame.toArrow())
    con.sql(f"CREATE OR REPLACE TABLE want AS {sql}")
    names = sorted(r[0] for r in con.sql("DESCRIBE want").fetchall())
    assert sorted(r[0] for r in con.sql("DESCRIBE got").fetchall()) == names
    columns = ", ".join(f'"{n}"' for n in names)
    assert con.sql("SELECT (SELECT count(*) FROM got) = (SELECT count(*) FROM want)").fetchall()[0][0]
    assert con.sql(f"SELECT count(*) FROM (SELECT {columns} FROM got EXCEPT ALL SELECT {columns} FROM want)").fetchall()[0][0] == 0
