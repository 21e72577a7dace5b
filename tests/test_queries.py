"""Every registered query of the library against its DuckDB oracle, or as rows; edges of sources and streams."""

from __future__ import annotations

import math
from dataclasses import replace

import duckdb
import pytest

from factorclust import plans
from factorclust.sources.tables import read_any, split_valid, write_any

REGISTRY = plans.load()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(small):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return c


def shown(v) -> str:
    return "nan" if isinstance(v, float) and math.isnan(v) else repr(v + 0.0) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(REGISTRY.QUERIES))
def test_query(name, spark, small, con):
    df = REGISTRY.QUERIES[name](spark, small)
    rows = df.collect()
    assert len(set(df.columns)) == len(df.columns)
    if name not in REGISTRY.ORACLES:
        assert rows
        return
    got = con.execute(REGISTRY.ORACLES[name])
    names = [c[0] for c in got.description]
    assert sorted(names) == sorted(df.columns)
    want = sorted(tuple(shown(r[names.index(c)]) for c in sorted(names)) for r in got.fetchall())
    assert sorted(tuple(shown(r[c]) for c in sorted(names)) for r in rows) == want


def test_relaxations_see_all_planted_points(spark, small):
    n = spark.read.parquet(f"{small}/embeddings.parquet").count()
    seen = {r.method: r.n for r in REGISTRY.QUERIES["relaxation_methods"](spark, small).collect()}
    assert {m: seen[m] for m in ("plain_nfk", "spectral", "nmf", "sampled_lloyd")} == dict.fromkeys(("plain_nfk", "spectral", "nmf", "sampled_lloyd"), n) and seen["sdp_small"] < 120


def test_distributed_query_fits_where_the_points_lie(spark, small, monkeypatch):
    from factorclust.operators import resident, solver

    monkeypatch.setattr(solver, "local_points", lambda *a: pytest.fail("points were gathered"))
    monkeypatch.setattr(solver, "fit_local", lambda *a, **k: pytest.fail("a local fit"))
    n = spark.read.parquet(f"{small}/embeddings.parquet").count()
    assert [tuple(r) for r in REGISTRY.QUERIES["nfk_distributed"](spark, small).collect()] == [("converged", 1.0, n, True)]
    whole = resident.fit
    monkeypatch.setattr(resident, "fit", lambda points, cfg, **more: whole(points, replace(cfg, max_iter=20), **more))
    assert REGISTRY.QUERIES["nfk_distributed"](spark, small).first().status == "capped"


def test_split_valid_tells_why(spark):
    inf, nan = float("inf"), float("nan")
    df = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [1.0, nan]), (5, [inf, 1.0]), (6, [None, 1.0])], "id long, x array<double>")
    good, bad = split_valid(df, 2)
    assert [r.id for r in good.collect()] == [1]
    assert {r.id: r.reason for r in bad.collect()} == {2: "null", 3: "width", 4: "nan", 5: "infinite", 6: "null entry"}


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_formats_come_back(kind, spark, tiny, tmp_path):
    n = spark.read.parquet(f"{tiny}/nation.parquet")
    write_any(n, str(tmp_path / kind), kind)
    back = read_any(spark, str(tmp_path / kind), kind, None if kind in ("orc", "parquet") else ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in n.schema))
    assert sorted(map(tuple, back.collect()), key=str) == sorted(map(tuple, n.collect()), key=str)


def test_filters_reach_the_scan(spark, tiny):
    plan = REGISTRY.QUERIES["rel_scan_pruned"](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull" in plan and "o_custkey" not in plan


def test_hot_path_has_no_python(spark, tiny):
    plan = REGISTRY.QUERIES["wcss_two_pass"](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_late_rows_are_dropped(spark, tmp_path):
    from pyspark.sql import functions as F

    from factorclust.streaming import streams

    for i, (ts, v) in enumerate((("2024-01-01 10:00:00", 1), ("2024-01-05 10:00:00", 2), ("2024-01-06 10:00:00", 5), ("2024-01-01 11:00:00", 3), ("2024-01-09 10:00:00", 4))):
        spark.sql(f"select timestamp'{ts}' as ts, {v} as cluster").coalesce(1).write.mode("append").parquet(str(tmp_path / f"in/{i}"))
    s = spark.readStream.schema("ts timestamp, cluster int").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("latestFirst", "false").parquet(str(tmp_path / "in"))
    got = {r.cluster for r in streams.run_to_end(streams.cluster_mix(s, F.col("cluster")), "late_out").collect()}
    assert 3 not in got and 1 in got


def test_membership_from_the_factor_equals_the_matrix_and_has_no_limit(spark, small):
    from pyspark.sql import functions as F

    from factorclust.functions.vectors import dot
    from factorclust.operators import partition
    from factorclust.sources.points import from_embeddings

    p = from_embeddings(spark, small).withColumn("cluster", F.pmod("id", F.lit(3)).cast("int"))
    f, m = partition.assignment_factor(p.select("id", "cluster")), partition.membership_matrix(p.select("id", "cluster"))
    rows = {r.i: r.s for r in m.groupBy("i").agg(F.sum("v").alias("s")).collect()}
    assert {r.i: pytest.approx(r.row_sum) for r in partition.membership_rows(f).collect()} == rows
    x = p.select(F.col("id").alias("i"), F.col("x").alias("a")).join(m, "i").join(p.select(F.col("id").alias("j"), F.col("x").alias("b")), "j")
    assert partition.membership_product(f, p).first()[0] == pytest.approx(x.agg(F.sum(F.col("v") * dot(F.col("a"), F.col("b")))).first()[0])
    many = spark.range(10_000).select("id", (F.col("id") % 7).cast("int").alias("cluster"))
    whole = partition.assignment_factor(many)
    assert all(r.ok for r in partition.check_membership(whole, 7).collect())
    assert not all(r.ok for r in partition.check_membership(whole.withColumn("weight", F.col("weight") * F.when(F.col("id") == 5, -1).otherwise(1)), 7).collect())


MADE_UP = "breakdown_case buffer_grid cnr_grid datasource_mixture fits_grid flops_grid memory_wall regime_check saved_grid smoothness_grid tile_grid udtf_mixture".split()


@pytest.mark.parametrize("name", MADE_UP)
def test_queries_read_a_given_table(name, spark, tiny, monkeypatch):
    from factorclust.plans import formulation, pieces, streams
    from factorclust.sources import points, tables

    read = []

    def seen(session, sf_dir, table, *more, **also):
        read.append(table)
        return tables.read_table(session, sf_dir, table, *more, **also)

    for module in (formulation, points, streams):
        monkeypatch.setattr(module, "read_table", seen)
    assert pieces.from_embeddings is points.from_embeddings
    assert REGISTRY.QUERIES[name](spark, tiny).count() and read
