"""The SQL given for operators, on the given tables and on one with links, nulls and near lines."""

from __future__ import annotations

import duckdb
import numpy as np
import pytest

from mapforge.llm import queries

SF = "/root/testdata/sf0.001"


def _compare(spark, folder: str, name: str) -> list:
    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        con.sql(f"create view {t} as select * from '{folder}/{t}.parquet{'' if folder == SF else '/*.parquet'}'")
    want = con.sql(queries.oracle_sql()[name])
    columns = sorted(want.columns)
    rows = con.sql(f"select {', '.join(columns)} from ({queries.oracle_sql()[name]})").fetchall()
    df = queries.queries()[name](spark, folder)
    assert sorted(df.columns) == columns
    got = [tuple(r) for r in df.select(*columns).collect()]
    assert sorted(map(str, got)) == sorted(map(str, rows))
    return got


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql_on_the_given_tables(spark, name):
    assert _compare(spark, SF, name)


def test_sql_on_tables_with_links(spark, tmp_path):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(40, 12))
    rows = [(k, v.tolist()) for k, v in enumerate(np.concatenate([x, x[:15] + rng.normal(scale=0.1, size=(15, 12)), x[3:6]]))] + [(90, None), (91, [0.0] * 12), (92, [1.0, 2.0]), (93, [float("nan")] * 12)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    words = [f"w{k}" for k in rng.integers(0, 500, 90)]
    other = [*words[:40], "new", *words[41:]]
    texts = [" ".join(words), " ".join(words), " ".join(other), "one two", "one two", "", None, "a line of sufficient length\na line of sufficient lengths\nshort\nshort\n \n\nb", "x\na line of sufficient lengthé\nA line of sufficient length"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert sum(r[2] > 0 for r in _compare(spark, str(tmp_path), "op5_embeddings")) > 10
    assert sum(r[2] > 0 for r in _compare(spark, str(tmp_path), "op7_near_duplicates")) == 5
    assert sum(r[-2] > 0 for r in _compare(spark, str(tmp_path), "op3_lines")) == 2
