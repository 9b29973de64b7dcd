"""Operators that attributes are often made with: as-of and range joins, coarser grains, JSON and array attributes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, by: list[str], at: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before ``at``, within ``by``: one window over the union. Equal times count as before."""
    l_cols = left.columns
    both = left.select(*l_cols, F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__side")).unionByName(right.select(*by, at, F.col(value).alias("__v"), F.lit(0).alias("__side")), allowMissingColumns=True)
    order = Window.partitionBy(*by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(f"as_of_{value}", F.last("__v", ignorenulls=True).over(order)).where("__side = 1").select(*l_cols, f"as_of_{value}")


def within(left: DataFrame, right: DataFrame, by: list[str], at: str, span: float) -> DataFrame:
    """Pairs with numeric ``at`` at most ``span`` apart, within ``by``: an equi-join on buckets of that width and their neighbours, then the exact test. Columns of
    the right side get the suffix ``_r``."""
    bucket = F.floor(F.col(at) / span)
    a = left.withColumn("__b", bucket)
    b = right.withColumn("__b", F.explode(F.array(bucket - 1, bucket, bucket + 1)))
    b = b.select(*by, "__b", *[F.col(c).alias(f"{c}_r") for c in right.columns if c not in by])
    return a.join(b, [*by, "__b"]).where(F.abs(F.col(at) - F.col(f"{at}_r")) <= span).drop("__b")


def json_attribute(column: str, path: str, kind: str = "long") -> Column:
    return F.get_json_object(column, path).cast(kind)


def running_pairs(steps: DataFrame, order: str, value: str) -> DataFrame:
    """Running sum over an ordered, small list of steps."""
    return steps.withColumn("running", F.sum(value).over(Window.orderBy(order).rowsBetween(Window.unboundedPreceding, 0)))


def largest_groups(df: DataFrame, attrs: list[str], top: int) -> DataFrame:
    """The ``top`` largest groups of a set, ties by value."""
    return df.groupBy(*attrs).agg(F.count("*").alias("size")).orderBy(F.desc("size"), *attrs).limit(top)


def rows_in_groups(df: DataFrame, attrs: list[str], alone: bool = False) -> DataFrame:
    """Rows that share their values with another row (or, ``alone``, that do not): a semi or anti join with the repeated values, null-safe."""
    again = df.groupBy(*attrs).agg(F.count("*").alias("__k")).where("__k > 1").select(*[F.col(a).alias(f"__{a}") for a in attrs])
    cond = None
    for a in attrs:
        same = F.col(a).eqNullSafe(F.col(f"__{a}"))
        cond = same if cond is None else cond & same
    return df.join(again, cond, "left_anti" if alone else "left_semi")
