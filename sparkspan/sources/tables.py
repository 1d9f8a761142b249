"""Trees in SQL: a table function over partitions, and a view."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf


def register_functions(spark: SparkSession) -> None:
    """``select * from emst_table(table(...) partition by key)`` over rows (key, pid, x0, x1)."""

    @udtf(returnType="grp bigint, lo bigint, hi bigint, d2 bigint")
    class EmstTable:
        def __init__(self):
            self.rows, self.key = [], None

        def eval(self, row):
            self.key = row["grp"]
            self.rows.append((row["pid"], row["x0"], row["x1"]))

        def terminate(self):
            import numpy as np

            from sparkspan.operators.kernels import prim

            t = np.array(self.rows, np.int64).reshape(-1, 3)
            for lo, hi, _, d2 in prim(t[:, 1:], t[:, 0]):
                yield self.key, lo, hi, d2

    spark.udtf.register("emst_table", EmstTable)


def register_emst_view(name: str, points: DataFrame, **options) -> None:
    from sparkspan.plans.emst import emst, finished

    finished(emst(points, **options).edges, "w").createOrReplaceTempView(name)
