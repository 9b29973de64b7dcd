"""Exact counts on all rows: unseparated pairs, verdicts, histograms, minimal keys.

Two rows are separated by a set of attributes if they differ on one of them. Rows equal on the set form a group, so the unseparated
pairs are the sum of size * (size - 1) / 2 over the groups. Nulls are equal to each other (``null_mode='value'``) or to nothing (``'distinct'``).
Counts of pairs are DECIMAL(38,0): they pass 64 bits beyond 3e9 rows.
"""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sepkey.operators import dealt
from sepkey.sources.stores import durable

Sets = list[tuple[str, list[str]]]
BIG = "decimal(38,0)"


def pairs(size: Column) -> Column:
    wide = size.cast("decimal(19,0)")
    return (wide * (wide - 1) / 2).cast(BIG)


def _groups(df: DataFrame, attrs: list[str], null_mode: str = "value") -> DataFrame:
    """One row (k) for each group."""
    size = F.count("*").alias("__size")  # an attribute may be called k
    if null_mode == "distinct" and attrs:
        some = F.array_contains(F.array(*[F.col(a).isNull() for a in attrs]), True)
        alone = df.where(some).select(F.lit(1).cast("long").alias("k"))
        return df.where(~some).groupBy(*attrs).agg(size).select(F.col("__size").alias("k")).unionByName(alone)
    return (df.groupBy(*attrs) if attrs else df.groupBy()).agg(size).select(F.col("__size").alias("k"))


def _summary() -> list[Column]:
    n = F.coalesce(F.sum("k"), F.lit(0))
    gamma = F.coalesce(F.sum(pairs(F.col("k"))), F.lit(0).cast(BIG))
    return [n.alias("n"), gamma.cast(BIG).alias("gamma"), F.sum((F.col("k") > 0).cast("long")).alias("groups"), F.coalesce(F.max("k"), F.lit(0)).alias("max_group")]


def _with_ratio(df: DataFrame) -> DataFrame:
    total = pairs(F.col("n"))
    share = F.when(total > 0, F.col("gamma").cast("double") / total.cast("double")).otherwise(F.lit(0.0))
    return df.withColumn("ratio", 1 - share)


def unseparated(df: DataFrame, attrs: list[str], null_mode: str = "value") -> DataFrame:
    """n, gamma, groups, max_group, ratio (of separated pairs) of one set: one shuffle, of at most one row per group and task."""
    out = _groups(df, attrs, null_mode).agg(*_summary())
    return _with_ratio(out.withColumn("groups", F.coalesce("groups", F.lit(0).cast("long"))))


def verdict_of(gamma: Column, n: Column, eps: float) -> Column:
    return F.when(gamma == 0, "key").when(gamma.cast("double") <= eps * pairs(n).cast("double"), "slack").otherwise("bad")


def verdict(df: DataFrame, attrs: list[str], eps: float, null_mode: str = "value") -> DataFrame:
    return unseparated(df, attrs, null_mode).withColumn("verdict", verdict_of(F.col("gamma"), F.col("n"), eps))


def is_key(df: DataFrame, attrs: list[str]) -> bool:
    """Stops at the first group of two rows that an output task meets."""
    return df.groupBy(*attrs).agg(F.count("*").alias("k")).where("k > 1").limit(1).isEmpty() if attrs else df.limit(2).count() < 2


#: Most sets that are counted by a group-by each.
PER_SET = 24


def _is_scan(df: DataFrame) -> bool:
    """Whether the rows come straight from files, so that reading them once for each set costs no more than the columns read."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return "Relation" in plan and not any(x in plan for x in ("Join", "Aggregate", "Window", "Generate", "Sort", "MapInArrow", "Union", "Limit"))


def unseparated_many(df: DataFrame, sets: Sets, strategy: str = "auto") -> DataFrame:
    """set_name, n, gamma, groups, max_group, ratio for each set.

    per_set: a group-by for each set, which reads its own columns only and groups by the values themselves; for a few sets of a table whose columns
    are stored apart. grouping_sets: rows are expanded before the partial aggregate; for a few sets. fingerprint: the expanded rows carry 128 bits of hash and
    no columns; for many sets (equal hashes of unequal values are expected only beyond 1e18 rows). lattice: the table is counted once by all attributes
    that occur, and every set from those counts; best where they compress the table. dealt: a shuffle for each of a few attributes, inside whose parts all
    sets with the attribute are counted; for many sets of a large table. auto: per_set for up to PER_SET sets of a plain scan; dealt for more sets than that
    and more than DEALT_CELLS rows times sets; else fingerprint."""
    sets = [(n, a) for n, a in dict((n, tuple(a)) for n, a in sets).items()]
    used = list(dict.fromkeys(a for _, attrs in sets for a in attrs))
    if strategy == "auto":
        strategy = "per_set" if len(sets) <= PER_SET and _is_scan(df) else "fingerprint"
        if len(sets) > PER_SET:
            if not _is_scan(df):  # joins are made once
                df = durable(df.select(*[F.col(f"`{a}`") for a in used]) if used else df.select(F.lit(0).alias("none")), "joined")
            if df.count() * len(sets) > DEALT_CELLS:
                strategy = "dealt"
    if strategy == "per_set":
        out = None
        for name, attrs in sets:
            one = _groups(df, list(attrs)).agg(*_summary()).select(F.lit(name).alias("set_name"), "n", "gamma", F.coalesce("groups", F.lit(0).cast("long")).alias("groups"), "max_group")
            out = one if out is None else out.unionByName(one)
        return _with_ratio(out.where("n > 0"))
    if strategy == "grouping_sets":
        distinct = list(dict.fromkeys(tuple(sorted(a, key=used.index)) for _, a in sets))
        ids = {}
        for attrs in distinct:
            ids[attrs] = sum(1 << (len(used) - 1 - i) for i, c in enumerate(used) if c not in attrs)
        counted = df.groupingSets([[F.col(c) for c in attrs] for attrs in distinct], *[F.col(c) for c in used]).agg(F.count("*").alias("k"), F.grouping_id().alias("gid"))
        per = counted.groupBy("gid").agg(*_summary())
        names = F.create_map(*[x for attrs, i in ids.items() for x in (F.lit(i).cast("long"), F.array(*[F.lit(n) for n, a in sets if tuple(sorted(a, key=used.index)) == attrs]))])
        return _with_ratio(per.select(F.explode(F.element_at(names, F.col("gid").cast("long"))).alias("set_name"), "n", "gamma", "groups", "max_group"))
    if strategy == "lattice":
        base = durable(df.groupBy(*used).agg(F.count("*").alias("k")), "cuboid")
        out = None
        for name, attrs in sets:
            one = (base.groupBy(*attrs) if attrs else base.groupBy()).agg(F.sum("k").alias("k")).agg(*_summary()).select(F.lit(name).alias("set_name"), "n", "gamma", "groups", "max_group")
            out = one if out is None else out.unionByName(one)
        return _with_ratio(out)
    if strategy == "dealt":
        return _dealt(df, sets)
    if strategy != "fingerprint":
        raise ValueError(strategy)
    marks = F.explode(F.array(*[F.struct(F.lit(i).alias("set_id"), fingerprint(list(a), df.schema).alias("f")) for i, (_, a) in enumerate(sets)])).alias("x")
    flat = df.select(marks).select("x.set_id", F.col("x.f.a").alias("a"), F.col("x.f.b").alias("b"))
    counted = flat.groupBy("set_id", "a", "b").agg(F.count("*").alias("k"))
    names = F.array(*[F.lit(n) for n, _ in sets])
    per = counted.groupBy("set_id").agg(*_summary())
    return _with_ratio(per.select(F.element_at(names, F.col("set_id") + 1).alias("set_name"), "n", "gamma", "groups", "max_group"))


#: Rows times sets beyond which a table is dealt out.
DEALT_CELLS = 20_000_000


def _dealt(df: DataFrame, sets: Sets) -> DataFrame:
    """Sets without an attribute to deal by (few values, or one very frequent) are counted from the groups of all their attributes together."""
    found, rest = dealt.counts(df, [tuple(a) for _, a in sets], df.count())
    rows = [(sets[i][0], n, gamma, groups, most) for i, (n, gamma, groups, most) in found.items()]
    out = df.sparkSession.createDataFrame(rows, f"set_name string, n long, gamma {BIG}, groups long, max_group long")  # one row a set
    if rest:
        names = F.array(*[F.lit(sets[i][0]) for i in rest])
        used = list(dict.fromkeys(a for i in rest for a in sets[i][1]))
        base = durable(df.groupBy(*used).agg(F.count("*").alias("__k")), "cuboid")
        marks = F.explode(F.array(*[F.struct(F.lit(j).alias("set_id"), fingerprint(list(sets[i][1]), df.schema).alias("f")) for j, i in enumerate(rest)])).alias("x")
        flat = base.select("__k", marks).select("__k", "x.set_id", F.col("x.f.a").alias("a"), F.col("x.f.b").alias("b"))
        per = flat.groupBy("set_id", "a", "b").agg(F.sum("__k").alias("k")).groupBy("set_id").agg(*_summary()).where("n > 0")
        out = out.unionByName(per.select(F.element_at(names, F.col("set_id") + 1).alias("set_name"), "n", "gamma", "groups", "max_group"))
    return _with_ratio(out)


def canonical(c: Column, kind: T.DataType) -> Column:
    """A value that hashes as ``c`` groups: zeros of either sign and all NaNs alike, nulls inside nested values as values of their own, maps
    whatever the order of their entries."""
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return F.when(F.isnan(c), F.lit(float("nan")).cast(kind)).when(c == 0, F.lit(0.0).cast(kind)).otherwise(c)
    flagged = lambda x, t: F.struct(x.isNull().alias("z"), canonical(x, t).alias("v"))
    if isinstance(kind, T.ArrayType):
        return F.struct(F.size(c).alias("n"), F.transform(c, lambda x: flagged(x, kind.elementType)).alias("v"))
    if isinstance(kind, T.MapType):
        return F.struct(F.size(c).alias("n"), F.array_sort(F.transform(F.map_entries(c), lambda x: F.struct(canonical(x["key"], kind.keyType).alias("k"), flagged(x["value"], kind.valueType).alias("v")))).alias("v"))
    if isinstance(kind, T.StructType):
        return F.struct(*[flagged(c.getField(f.name), f.dataType).alias(f"f{i}") for i, f in enumerate(kind)])
    return c


def fingerprint(attrs: list[str], schema: T.StructType) -> Column:
    """128 bits of hash of a row's values. Each value hashes with its null flag, so that a null is a value of its own."""
    parts = [x for a in attrs for x in (F.col(a).isNull(), canonical(F.col(a), schema[a].dataType))]
    return F.struct(F.xxhash64(F.lit(1), *parts).alias("a"), F.xxhash64(F.lit(2), F.lit("second"), *parts).alias("b"))


def clique_histogram(df: DataFrame, attrs: list[str]) -> DataFrame:
    """size, groups: how many groups have each size."""
    return _groups(df, attrs).groupBy(F.col("k").alias("size")).agg(F.count("*").alias("groups"))


#: Most pairs that are listed without being asked to; more are refused, never cut.
LISTED_PAIRS = 200_000_000
#: About the pairs that one task forms, and the most tasks asked for.
TASK_PAIRS, MOST_TASKS = 4_000_000, 2000
#: Most rows that are broadcast; more are joined by a shuffle.
BROADCAST_NODES = 1_000_000


def unseparated_edges(df: DataFrame, attrs: list[str], row_id: str, bounded: bool = True) -> DataFrame:
    """The unseparated pairs themselves (a < b). They are counted first, and refused beyond ``LISTED_PAIRS``; with ``bounded=False`` any number streams
    through, for a caller that aggregates them."""
    size = unseparated(df, attrs).first()
    found = int(size.gamma)
    if bounded and found > LISTED_PAIRS:
        raise ValueError(f"{found} unseparated pairs are too many to list; count them with unseparated(), or take unseparated_classes()")
    left = df.select(F.col(row_id).alias("a"), F.struct(*attrs).alias("v"))
    right = df.select(F.col(row_id).alias("b"), F.struct(*attrs).alias("w"))
    same = F.col("v").eqNullSafe(F.col("w"))
    if found > TASK_PAIRS and size.n <= BROADCAST_NODES:  # few rows with many pairs: dealt by pairs, not by bytes
        left, right = left.repartition(min(MOST_TASKS, math.ceil(found / TASK_PAIRS))), F.broadcast(right)
    return left.join(right, same & (F.col("a") < F.col("b"))).select("a", "b")


def unseparated_classes(df: DataFrame, attrs: list[str], row_id: str) -> DataFrame:
    """The same relation without its pairs: each row's id, its class (the least id of its group) and its number of links."""
    groups = df.groupBy(*[F.col(a).alias(f"__v{i}") for i, a in enumerate(attrs)]).agg(F.min(row_id).alias("class_id"), (F.count("*") - 1).alias("links"))
    same = F.lit(True)
    for i, a in enumerate(attrs):
        same = same & F.col(a).eqNullSafe(F.col(f"__v{i}"))
    return df.join(groups, same).select(row_id, "class_id", "links")


def open_paths(edges: DataFrame) -> DataFrame:
    """Paths a-b-c of unseparated pairs whose ends are separated: none, as groups are cliques.

    On such a path c is a neighbour of b and not of a, so that a and b, and likewise b and c, have unlike neighbourhoods (themselves included). Each node's
    neighbourhood is hashed to sums of 124 bits in one pass over the edges; only edges between unlike ones are kept, and paths are formed of these alone."""
    pieces = [F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("__x")), shift).bitwiseAND(0x7FFFFFFF) for seed in (1, 2) for shift in (0, 33)]
    ends = edges.select(F.explode(F.array(F.struct(F.col("a").alias("node"), F.col("b").alias("__x")), F.struct(F.col("b").alias("node"), F.col("a").alias("__x")))).alias("e")).select("e.node", "e.__x")
    around = ends.select("node", *[p.alias(f"__p{i}") for i, p in enumerate(pieces)]).groupBy("node").agg(*[F.sum(f"__p{i}").alias(f"__p{i}") for i in range(len(pieces))])
    closed = around.withColumn("__x", F.col("node")).select("node", F.struct(*[(F.col(f"__p{i}") + p).alias(f"p{i}") for i, p in enumerate(pieces)]).alias("near"))
    nodes = durable(closed, "nodes")
    near = F.broadcast(nodes) if nodes.count() <= BROADCAST_NODES else nodes
    sided = edges.join(near.select(F.col("node").alias("a"), F.col("near").alias("__na")), "a").join(near.select(F.col("node").alias("b"), F.col("near").alias("__nb")), "b")
    uneven = durable(sided.where(F.col("__na") != F.col("__nb")).select("a", "b"), "uneven")
    if uneven.isEmpty():
        return uneven.select("a", F.col("b").alias("c"))
    both = uneven.unionByName(uneven.select(F.col("b").alias("a"), F.col("a").alias("b")))
    paths = both.join(both.select(F.col("a").alias("b"), F.col("b").alias("c")), "b").where("a < c").select("a", "c").distinct()
    return paths.join(edges.select("a", F.col("b").alias("c")), ["a", "c"], "left_anti")


def marginal_gain(df: DataFrame, attrs: list[str], more: str) -> DataFrame:
    """gamma_before, gamma_after and gain of one more attribute, from one pass: groups of both, re-aggregated to groups of the first."""
    fine = df.groupBy(*attrs, more).agg(F.count("*").alias("k"))
    coarse = fine.groupBy(*attrs).agg(F.sum("k").alias("n"), F.sum(pairs(F.col("k"))).alias("after"))
    out = coarse.agg(F.coalesce(F.sum(pairs(F.col("n"))), F.lit(0).cast(BIG)).alias("gamma_before"), F.coalesce(F.sum("after"), F.lit(0).cast(BIG)).cast(BIG).alias("gamma_after"))
    return out.withColumn("gain", F.col("gamma_before") - F.col("gamma_after"))


def minimal_keys(df: DataFrame, largest: int, attrs: list[str] | None = None) -> list[list[str]]:
    """All keys of at most ``largest`` attributes that hold no smaller key, by levels; supersets of keys are never counted. Each level is one pass."""
    attrs = attrs or df.columns
    found: list[frozenset] = []
    for size in range(1, largest + 1):
        level = [c for c in combinations(attrs, size) if not any(k <= set(c) for k in found)]
        if not level:
            break
        counted = unseparated_many(df, [(str(i), list(c)) for i, c in enumerate(level)])
        keys = sorted(int(r.set_name) for r in counted.where("gamma = 0").select("set_name").collect())  # at most C(m, size) rows
        found += [frozenset(level[i]) for i in keys]
    order = {a: i for i, a in enumerate(attrs)}
    return sorted((sorted(k, key=order.get) for k in found), key=lambda k: (len(k), [order[a] for a in k]))
