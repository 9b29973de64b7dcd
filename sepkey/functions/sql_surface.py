"""The methods from SQL: scalar functions, an aggregate, a table function over a sample, and views.

After ``register(spark)``::

    SELECT separation_verdict(gamma, n, 0.001) FROM ...
    SELECT noncollision(k, 3) FROM (SELECT count(*) AS k FROM t GROUP BY city)
    SELECT * FROM greedy_trace(TABLE(sample_t) WITH SINGLE PARTITION)
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sepkey.functions import bounds
from sepkey.operators import sampling
from sepkey.sources.stores import ship


class GreedyTrace:
    """Steps of the greedy key over the rows of a sample: step, attr, gamma_after. The sample's size depends on its attributes and eps, not on
    the table, so one partition holds it."""

    def __init__(self):
        self.codes: dict[str, list[int]] = {}
        self.seen: dict[str, dict] = {}

    def eval(self, row):
        for name, value in row.asDict().items():
            known = self.seen.setdefault(name, {})
            self.codes.setdefault(name, []).append(known.setdefault("NaN" if value != value else str(value) if isinstance(value, (list, dict)) else value, len(known)))

    def terminate(self):
        from sepkey.operators import mincover

        key = mincover.refine_greedy({k: np.array(v, np.int64) for k, v in self.codes.items()}, list(self.codes))
        for i, (attr, gamma) in enumerate(key.steps):
            yield i + 1, attr, gamma


def register(spark: SparkSession) -> None:
    ship(spark)

    @F.pandas_udf("double")
    def noncollision(size: pd.Series, draws: pd.Series) -> float:
        """The chance that draws without replacement fall into different groups, from the groups' sizes."""
        hist = size.value_counts()
        return float(bounds.noncollision(list(zip(hist.index.tolist(), hist.tolist(), strict=True)), int(draws.iloc[0]), False))

    spark.udf.register("noncollision", noncollision)
    spark.udtf.register("greedy_trace", F.udtf(GreedyTrace, returnType="step: bigint, attr: string, gamma_after: bigint"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pairs_of(k BIGINT) RETURNS DECIMAL(38,0) RETURN CAST(CAST(k AS DECIMAL(19,0)) * (CAST(k AS DECIMAL(19,0)) - 1) / 2 AS DECIMAL(38,0))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION separation_verdict(gamma DECIMAL(38,0), n BIGINT, eps DOUBLE) RETURNS STRING RETURN CASE WHEN gamma = 0 THEN 'key' WHEN CAST(gamma AS DOUBLE) <= eps * CAST(n AS DOUBLE) * (n - 1) / 2 THEN 'slack' ELSE 'bad' END")


def sample_view(df: DataFrame, name: str, r: int, seed: int, identity: list[Column], attrs: list[str]) -> None:
    """The temporary view ``sample_<name>`` of r tuples."""
    sampling.tuples(df, r, seed, identity).select(*attrs).createOrReplaceTempView(f"sample_{name}")
