"""Inputs on which few samples must fail, trials on them, and the reconstruction game of the sketch's lower bound."""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sepkey.functions import bounds, portable
from sepkey.operators import exact, sampling


def grid_values(eps: float) -> int:
    """The most values for which every single attribute of the grid is bad: below 1/eps."""
    return math.ceil(1 / eps) - 1


def grid(spark: SparkSession, q: int, m: int) -> DataFrame:
    """All q^m tuples over 1..q: columns x1..xm."""
    return spark.range(q**m).select(*[(F.floor(F.col("id") / F.lit(q**i)).cast("long") % q + 1).cast("int").alias(f"x{i + 1}") for i in range(m)])


def grid_on(df: DataFrame, attrs: list[str]) -> DataFrame:
    """All tuples over the values that the attributes, few-valued ones, have in ``df``."""
    out = df.select(attrs[0]).distinct()
    for a in attrs[1:]:
        out = out.crossJoin(df.select(a).distinct())
    return out


def grid_trials(spark: SparkSession, q: int, m: int, sizes: list[int], trials: int, seed: int) -> DataFrame:
    """r, detected: the share of trials in which r draws from the grid (with replacement: attributes are independent) collide on each single attribute."""
    top = max(sizes)
    cells = spark.range(trials * top).select((F.col("id") / top).cast("long").alias("trial"), (F.col("id") % top).alias("draw"), F.explode(F.sequence(F.lit(1), F.lit(m))).alias("attr"))
    value = F.pmod(portable.number(F.concat_ws("|", F.lit(str(seed)), "trial", "draw", "attr")), F.lit(q))
    return _detected(cells.withColumn("value", value), sizes).select("r", "detected")


def grid_trials_on(df: DataFrame, key: str, q: int, m: int, sizes: list[int], seed: int) -> DataFrame:
    """r, detected, hits, trials: the same with the rows of ``df`` as draws. In order of ``key`` each max(sizes) rows are a trial, and a row's m values follow
    from its key; of the last trial, which may be short, only sizes that it reaches are counted."""
    top, rows = max(sizes), sampling.ordinals(df.select(key), [F.col(key)])
    n = df.count()
    # a trial stays in one part: what follows needs no further shuffle of the m-fold cells
    draws = rows.select((F.col("ordinal") / top).cast("long").alias("trial"), (F.col("ordinal") % top).alias("draw"), key).repartition("trial")
    cells = draws.withColumn("attr", F.explode(F.sequence(F.lit(1), F.lit(m))))
    value = F.pmod(portable.draw(seed, F.col(key), F.col("attr").cast("string")), F.lit(q))
    return _detected(cells.withColumn("value", value), sizes, F.col("trial") * top + F.col("r") <= n)


def _detected(cells: DataFrame, sizes: list[int], whole: Column | None = None) -> DataFrame:
    cells = cells.withColumn("r", F.explode(F.array(*[F.lit(x) for x in sizes]))).where(F.col("draw") < F.col("r"))
    cells = cells if whole is None else cells.where(whole)
    met = cells.groupBy("r", "trial", "attr", "value").agg(F.count("*").alias("k")).groupBy("r", "trial", "attr").agg((F.max("k") > 1).alias("hit"))
    return met.groupBy("r", "trial").agg(F.bool_and("hit").alias("all_hit")).groupBy("r").agg(F.avg(F.col("all_hit").cast("double")).alias("detected"), F.count_if("all_hit").alias("hits"), F.count("*").alias("trials"))


def planted(spark: SparkSession, n: int, eps: float, m: int = 2) -> DataFrame:
    """x1: one value on the least cluster that is bad, unique elsewhere; x2: a key; further attributes constant."""
    c = bounds.planted_size(n, eps)
    rows = spark.range(n)
    return rows.select(F.when(F.col("id") < c, F.lit(-1)).otherwise(F.col("id")).cast("long").alias("x1"), F.col("id").alias("x2"), *[F.lit(0).alias(f"x{i}") for i in range(3, m + 1)])


def planted_on(df: DataFrame, identity: list, n: int, eps: float, seed: int, name: str = "planted") -> DataFrame:
    """``df`` with a planted attribute: c rows of the least ranks share a value, all others have one of their own. Rows of one identity have equal ranks:
    they are numbered, so that the cluster has c rows and the values outside are distinct all the same."""
    c = bounds.planted_size(n, eps)
    ids = [f"__id{i}" for i in range(len(identity))]
    ranked = df.select("*", *[x.alias(i) for x, i in zip(identity, ids, strict=True)]).withColumn("__rank", portable.rank(seed, [F.col(i) for i in ids]))
    inside = ranked.select("__rank").orderBy("__rank").limit(c).groupBy(F.col("__rank").alias("__last")).agg(F.count("*").alias("__take"))
    last = inside.agg(F.max(F.struct("__last", "__take")).alias("x")).select("x.*")  # one row: the last rank, and how many of its rows are taken
    nth = F.row_number().over(Window.partitionBy("__rank").orderBy(F.xxhash64(*df.columns)))
    numbered = ranked.withColumn("__nth", nth).crossJoin(F.broadcast(last))
    taken = (F.col("__rank") < F.col("__last")) | ((F.col("__rank") == F.col("__last")) & (F.col("__nth") <= F.col("__take")))
    return numbered.withColumn(name, F.when(taken, "cluster").otherwise(F.concat_ws("|", *[F.coalesce(F.col(i).cast("string"), F.lit("\\N")) for i in ids], "__rank", "__nth"))).select(*df.columns, name)


def planted_trials(spark: SparkSession, n: int, c: int, sizes: list[int], trials: int, seed: int) -> DataFrame:
    """r, missed: the share of trials in which r draws with replacement hold at most one row of the cluster."""
    top = max(sizes)
    draws = spark.range(trials * top).select((F.col("id") / top).cast("long").alias("trial"), (F.col("id") % top).alias("draw"))
    inside = F.pmod(portable.number(F.concat_ws("|", F.lit(str(seed)), "trial", "draw")), F.lit(n)) < c
    each = draws.withColumn("inside", inside).withColumn("r", F.explode(F.array(*[F.lit(x) for x in sizes]))).where(F.col("draw") < F.col("r"))
    return each.groupBy("r", "trial").agg(F.count_if("inside").alias("k")).groupBy("r").agg(F.avg((F.col("k") <= 1).cast("double")).alias("missed"))


def weighted_matrix(spark: SparkSession, k: int, t: int, m: int, seed: int) -> DataFrame:
    """row 0..kt-1 and columns c1..cm of zeros and ones, k ones in each column: the k least MD5 ranks."""
    cells = spark.range(k * t).select(F.col("id").alias("row"), F.explode(F.sequence(F.lit(1), F.lit(m))).alias("col"))
    nth = F.row_number().over(Window.partitionBy("col").orderBy(F.md5(F.concat_ws("|", F.lit(str(seed)), "row", "col"))))
    return cells.withColumn("bit", (nth <= k).cast("int")).groupBy("row").pivot("col", list(range(1, m + 1))).agg(F.max("bit")).select("row", *[F.col(str(i)).alias(f"c{i}") for i in range(1, m + 1)])


def block_table(matrix: DataFrame, n: int, m: int) -> DataFrame:
    """The matrix over as many rows of ones, beside the identity over zeros: row, c1..cm, e0..e(n-1)."""
    unit = lambda r: [(F.col("row") == i).cast("int").alias(f"e{i}") for i in range(n)] if r else [F.lit(0).alias(f"e{i}") for i in range(n)]
    upper = matrix.select("row", *[f"c{i}" for i in range(1, m + 1)], *unit(True))
    lower = matrix.select((F.col("row") + n).alias("row"), *[F.lit(1).alias(f"c{i}") for i in range(1, m + 1)], *unit(False))
    return upper.unionByName(lower)


def block_counts(df: DataFrame, key: str, cases: list[tuple[int, int, int]]) -> list[int]:
    """Unseparated pairs of guesses (k, g, u) in the block table of a column whose ones are the first k rows of ``df`` by ``key``: the guess is of g rows, u of
    them ones. Its own unit columns set each guessed row apart; the other upper rows fall to the n lower ones, or together, by their bit. All rows
    are numbered and counted, in one pass for all cases."""
    rows = sampling.ordinals(df.select(key), [F.col(key)])
    counts = []
    for i, (k, g, u) in enumerate(cases):
        out = (F.col("ordinal") < k - u) | (F.col("ordinal") >= k - u + g)
        counts += [F.count_if(out & (F.col("ordinal") < k)).alias(f"one{i}"), F.count_if(out & (F.col("ordinal") >= k)).alias(f"zero{i}")]
    got = rows.agg(F.count("*").alias("n"), *counts).first()
    return [bounds.pairs_of(got.n + got[f"one{i}"]) + bounds.pairs_of(got[f"zero{i}"]) for i in range(len(cases))]


def guess_attrs(col: int, rows: list[int] | tuple[int, ...]) -> list[str]:
    return [f"c{col}", *[f"e{r}" for r in rows]]


def check(k: int, m: int, eps: float) -> dict:
    """The game's precondition, and its sizes once the column is counted in (k + 1 attributes of m + n)."""
    return {"wide_enough": m >= k / math.sqrt(eps), "k": k + 1}


def reconstruct(estimate, k: int, t: int, m: int, eps: float) -> dict[int, tuple[int, ...] | None]:
    """For each column the first guess of k rows whose estimate is under the threshold. ``estimate(sets)`` maps names to numbers (None: small)."""
    n, limit = k * t, bounds.decoder_threshold(t, k, eps)
    out = {}
    for col in range(1, m + 1):
        guesses = list(combinations(range(n), k))
        answers = estimate([(f"{col}:{i}", guess_attrs(col, g)) for i, g in enumerate(guesses)])
        out[col] = next((g for i, g in enumerate(guesses) if (a := answers[f"{col}:{i}"]) is not None and a <= limit), None)
    return out


def exact_estimates(table: DataFrame):
    """An estimator without error, for ``reconstruct``: group counts on all rows."""

    def estimate(sets):
        return {r.set_name: int(r.gamma) for r in exact.unseparated_many(table, sets).select("set_name", "gamma").collect()}

    return estimate


def sketch_estimates(sketch):
    def estimate(sets):
        return {r.set_name: r.gamma_hat for r in sketch.estimate_many(sets).collect()}

    return estimate


def hamming(matrix: dict[int, set[int]], guess: dict[int, tuple[int, ...] | None]) -> dict:
    """Differing cells over all, and by column. matrix: the rows of ones of each column."""
    by = {c: len(ones ^ set(guess.get(c) or ())) for c, ones in matrix.items()}
    return {"cells": sum(by.values()), "by_column": by}
