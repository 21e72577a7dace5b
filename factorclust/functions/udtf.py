"""Table functions for SQL users: cluster a table of points, and a planted mixture."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register_table_functions(spark: SparkSession) -> None:
    """Registers ``nfk_cluster(TABLE(points), k, rank)`` and ``planted_mixture(n, d, k, gamma, seed)``."""

    @udtf(returnType="id: bigint, cluster: int, status: string")
    class NfkCluster:
        """Gathers the rows of its partition (id, x), so it is for tables of a size one worker holds: partition by a run id."""

        def __init__(self):
            self.rows: list[tuple] = []
            self.k = self.rank = 0

        def eval(self, row, k: int, rank: int):
            self.rows.append((row["id"], list(row["x"])))
            self.k, self.rank = k, rank

        def terminate(self):
            import numpy as np

            from factorclust.operators import rounding, solver
            from factorclust.operators.kernel import Config

            if not self.rows:
                return
            rows = sorted(self.rows)
            ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], float)
            fit = solver.fit_local(x, Config(k=self.k, rank=self.rank), ids)
            for i, c in zip(ids.tolist(), rounding.canonical_np(rounding.round_columns(fit.factor, self.k)).tolist(), strict=True):
                yield i, c, fit.status

    @udtf(returnType="id: bigint, x: array<double>, truth: int")
    class PlantedMixture:
        def eval(self, n: int, d: int, k: int, gamma: float, seed: int):
            import numpy as np

            from factorclust.sources.points import mixture_rows

            for at in range(0, n, 4096):
                ids = np.arange(at, min(n, at + 4096))
                x, truth = mixture_rows(ids, n, d, k, float(gamma), seed)
                for i, v, t in zip(ids.tolist(), x.tolist(), truth.tolist(), strict=True):
                    yield i, v, t

    spark.udtf.register("nfk_cluster", NfkCluster)
    spark.udtf.register("planted_mixture", PlantedMixture)
