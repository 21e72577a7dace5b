"""The fit with points and state in two bucketed tables."""

from __future__ import annotations

import numpy as np

from factorclust.operators import kernel, paired, solver
from factorclust.operators.kernel import Config


def test_paired_tables_step_alike_without_a_shuffle(spark, tmp_path):
    rng = np.random.default_rng(0)
    x = np.eye(5)[:3][np.arange(150) % 3] * 6 + rng.standard_normal((150, 5))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, x array<double>")
    cfg = Config(k=3, max_iter=4)
    model = paired.fit(df, cfg, buckets=3, tile_rows=20)
    local = solver.fit_local(x, cfg)
    got = model.factor().orderBy("id").toPandas()
    assert np.abs(np.stack(got.f) - local.factor).max() < 1e-9 and len(model.trace) == 4
    was = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        driver = kernel.Driver(cfg, 150, 5)
        control = driver.first(solver.add_up(model.state.select("sums"), 5, cfg.r))
        tables = [t.name for t in spark.catalog.listTables() if t.name.startswith("factorclust_")]
        points = spark.table(next(t for t in tables if "points" in t))
        state = spark.table(next(t for t in tables if "state" in t))
        plan = paired.sweep(points, state, control, 5, cfg.r)._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", was)
        paired.drop_tables(spark)
