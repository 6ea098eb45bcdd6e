"""Readers and sinks."""

import pytest

from dgprop.plans.lineage import plan_text
from dgprop.schemas import check
from dgprop.sources import files


def test_text_edges(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1 2\n3 4 2.5\n5 6 1 99\nbroken\n\n7 x\n")
    got = sorted(tuple(r) for r in files.read_edge_text(spark, str(tmp_path / "e.txt")).collect())
    assert got == [(1, 2, 1.0, None), (3, 4, 2.5, None), (5, 6, 1.0, 99)]


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json"])
def test_round_trip(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, 2, 1.5, 7), (3, 4, 0.5, 8)], files.EDGE_LIST)
    path = str(tmp_path / fmt)
    files.export(df, path, fmt)
    options = {"header": "true"} if fmt == "csv" else {}
    assert sorted(map(tuple, files.read_edges(spark, path, fmt, **options).collect())) == sorted(map(tuple, df.collect()))


def test_steps_are_replaced_one_by_one_and_pruned(spark, tmp_path):
    path = str(tmp_path / "z")
    rows = lambda steps, v: spark.createDataFrame([(s, 1, [v]) for s in steps], "step int, node bigint, z array<double>")
    files.write_steps(rows([1, 2, 3], 1.0), path)
    files.write_steps(rows([2], 9.0), path)
    got = files.read_steps(spark, path, 2, 3)
    assert sorted((r["step"], r["z"][0]) for r in got.collect()) == [(2, 9.0), (3, 1.0)]
    assert "PartitionFilters: [isnotnull(step" in plan_text(got)


def test_normalise_and_check(spark):
    df = spark.createDataFrame([(5, "a", 1, 2)], "t bigint, k string, u bigint, v bigint")
    r = files.normalise(df, "t * 1000", "u", "v + 100").head()
    assert (r["ts_us"], r["src"], r["dst"], r["w"], r["kind"]) == (5000, 1, 102, 1.0, "add_edge")
    with pytest.raises(ValueError):
        check(df, "u int")
    with pytest.raises(ValueError):
        check(df, "missing bigint")


def test_nearest_vectors_on_copies_zero_and_null_vectors(spark, tmp_path, monkeypatch):
    """As in SQL, in blocks smaller than the table: copies, near ones, vectors without a direction, null ones, repeated ids; more copies than are asked for."""
    import duckdb
    import numpy as np

    from dgprop.sources import tables as T
    from dgprop.workloads import load

    rng = np.random.default_rng(5)
    rows = [(i, rng.integers(-3, 4, 8).astype(float).tolist()) for i in range(120)]
    rows += [(200 + i, rows[7][1]) for i in range(9)] + [(300 + i, [x * 2 for x in rows[9][1]]) for i in range(9)]
    rows += [(400 + i, None) for i in range(3)] + [(500, [0.0] * 8), (501, [0.0] * 8), (7, rows[7][1]), (8, rows[30][1])]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    monkeypatch.setattr(T, "LOOKING", 16)
    monkeypatch.setattr(T, "SEEN", 32)
    monkeypatch.setattr(T, "AT_ONCE", 5)
    got = sorted(tuple(r) for r in T.nearest_vectors(spark, str(tmp_path)).collect())
    duckdb.sql(f"CREATE OR REPLACE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    assert got == sorted(duckdb.sql(load()[1]["gr_knn_edges"]).fetchall())


def test_nearest_vectors_multiply_blocks(spark, tmp_path):
    """Blocks of vectors go through arrays: no row for each pair of vectors, of which a table of this size has nine millions."""
    import numpy as np

    from dgprop.sources import tables as T

    e = np.random.default_rng(6).normal(size=(3_000, 4))
    spark.createDataFrame([(i, x) for i, x in enumerate(e.tolist())], "vec_id bigint, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    df = T.nearest_vectors(spark, str(tmp_path))
    assert df.count() == 15_000
    assert "zip_with" not in plan_text(df)
