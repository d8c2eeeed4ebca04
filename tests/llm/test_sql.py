"""Queries with SQL against DuckDB, on given tables and on hand-made ones."""

import duckdb
import pytest

from chartrel.llm import queries

from .conftest import frame


def rows_of(df):
    return sorted(map(str, (tuple(r) for r in df.select(*sorted(df.columns)).collect())))


def sql_rows(where, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        try:
            con.sql(f"create view {t} as select * from read_parquet('{where}/{t}.parquet{'/*.parquet' if 'sf0' not in str(where) else ''}')")
        except duckdb.IOException:
            pass
    got = con.sql(queries.ORACLES[name])
    at = [got.columns.index(c) for c in sorted(got.columns)]
    return sorted(str(tuple(r[i] for i in at)) for r in got.fetchall())


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_given_tables(spark, mid, name):
    assert rows_of(queries.QUERIES[name](spark, mid)) == sql_rows(mid, name)


def test_lines_of_hand_made_texts(spark, tmp_path):
    text = ["All rights reserved.\na b c d e f g\n\n 7 \nonly {0}", "one two three four five six seven {0} nine\n| {0} | {0}{0} |", "x" * 40 + "\n" + "年{0}" + "月" * 40, None, ""]
    rows = [(i, t.format("abcd"[i % 4] if i % 3 else i) if t else t) for i, t in enumerate(text * 5)] + [(3, "All rights reserved.\nkept line of another row"), (None, "All rights reserved.")]
    frame(spark, rows).write.parquet(f"{tmp_path}/documents.parquet")
    assert rows_of(queries.op8_line_dedup(spark, str(tmp_path))) == sql_rows(tmp_path, "op8_line_dedup")


def test_vectors_in_chains(spark, tmp_path):
    import math

    rows = [(50 - k, [math.cos(k * 0.4), math.sin(k * 0.4)]) for k in range(10)] + [(7, [1.0, 0.0]), (7, [5.0, 0.0]), (8, None), (9, [0.0, 0.0]), (10, [float("nan"), 1.0]), (11, [1.0, None]), (None, [1.0, 0.0]), (12, [1.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = rows_of(queries.op10_embedding_neardup(spark, str(tmp_path)))
    assert got == sql_rows(tmp_path, "op10_embedding_neardup") and len(set(got)) > 8
