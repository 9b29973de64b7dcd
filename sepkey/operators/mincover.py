"""Small separation keys: greedy and exhaustive covers, over samples of tuples or pairs, or over all rows.

A trace is a list of steps (attribute, pairs still together after it). Where rows or pairs that no attribute tells apart are left, the search ends
with what remains; it never loops.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sepkey.functions import bounds
from sepkey.operators import exact, filters, setcover
from sepkey.sources.stores import durable


@dataclass
class Key:
    attrs: list[str]
    steps: list[tuple[str, int]] = field(default_factory=list)
    residual: int = 0

    @property
    def complete(self) -> bool:
        return self.residual == 0


def _candidates(attrs: list[str], exclude: list[str] | None, must: list[str] | None) -> tuple[list[str], list[str]]:
    must = list(must or [])
    return must, [a for a in attrs if a not in must and a not in (exclude or [])]


# -- on all rows


def instance(df: DataFrame, row_id: str, attrs: list[str], bounded: bool = True) -> DataFrame:
    """All pairs of rows (a < b) with one flag for each attribute on which they differ; refused beyond ``exact.LISTED_PAIRS``. With ``bounded=False`` any
    number streams through, for a caller that aggregates them (``greedy_pairs`` does)."""
    n = df.count()
    if bounded and bounds.pairs_of(n) > exact.LISTED_PAIRS:
        raise ValueError("too many pairs to list; greedy_full needs none")
    left = df.select(F.col(row_id).alias("a"), F.struct(*attrs).alias("l"))
    right = df.select(F.col(row_id).alias("b"), F.struct(*attrs).alias("r"))
    if bounds.pairs_of(n) > exact.TASK_PAIRS and n <= exact.BROADCAST_NODES:  # few rows with many pairs: dealt by pairs, not by bytes
        left, right = left.repartition(min(exact.MOST_TASKS, -(-bounds.pairs_of(n) // exact.TASK_PAIRS))), F.broadcast(right)
    return left.join(right, F.col("a") < F.col("b")).select("a", "b", *[(~F.col(f"l.{x}").eqNullSafe(F.col(f"r.{x}"))).alias(x) for x in attrs])


def greedy_pairs(pairs_df: DataFrame, attrs: list[str], exclude: list[str] | None = None, must_include: list[str] | None = None) -> Key:
    """Greedy cover of explicit pairs (flags: differs): each round counts what every attribute would cover and drops the covered pairs. Pairs with the same
    flags are covered by the same attributes: they are counted in one pass, and the rounds work on these counts."""
    forced, rest = _candidates(attrs, exclude, must_include)
    flags = [F.col(a).alias(f"f{i}") for i, a in enumerate(attrs)]  # an attribute may be called count
    left, key = durable(pairs_df.groupBy(*flags).agg(F.count("*").alias("pairs")).select(*[F.col(f"f{i}").alias(a) for i, a in enumerate(attrs)], F.col("pairs").alias(_PAIRS)), "pairs"), Key([])
    total = left.agg(F.coalesce(F.sum(_PAIRS), F.lit(0))).first()[0]
    while total:
        names = forced[:1] or rest
        if not names:
            break
        counts = left.agg(*[F.coalesce(F.sum(F.when(F.col(a), F.col(_PAIRS))), F.lit(0)).alias(a) for a in names]).first().asDict()
        pick = max(names, key=lambda a: counts[a])
        if counts[pick] == 0 and not forced:
            break
        forced, rest = forced[1:], [a for a in rest if a != pick]
        left = durable(left.where(~F.col(pick)), "pairs")
        total -= counts[pick]
        key.attrs.append(pick)
        key.steps.append((pick, total))
    key.attrs += forced
    key.residual = total
    return key


_PAIRS = "__pairs"
_CLASS = "__class"


def score_round(live: DataFrame, candidates: list[str]) -> DataFrame:
    """attr, gamma: the pairs of rows of one class that each candidate leaves together, from one pass over the live rows."""
    return exact.unseparated_many(live, [(a, [_CLASS, a]) for a in candidates]).select(F.col("set_name").alias("attr"), "gamma")


def split_classes(live: DataFrame, pick: str) -> DataFrame:
    """The live rows with their classes split by ``pick``, which leaves; rows that are alone in their class go."""
    groups = live.groupBy(_CLASS, F.col(pick).alias("__value")).agg(F.count("*").alias("k")).where("k > 1")
    groups = durable(groups.select(_CLASS, "__value", F.monotonically_increasing_id().alias("__next")), "classes")
    few = F.broadcast(groups) if groups.count() * _CLASS_BYTES <= BROADCAST_BYTES and _narrow(live, pick) else groups
    both = live.join(few.withColumnRenamed(_CLASS, "__of"), (F.col(_CLASS) == F.col("__of")) & F.col(pick).eqNullSafe(F.col("__value")))
    return durable(both.select(F.col("__next").alias(_CLASS), *[c for c in live.columns if c not in (_CLASS, pick)]), "live")


#: Bytes that a broadcast of classes may take, and about the bytes of one class of a value of fixed size.
BROADCAST_BYTES, _CLASS_BYTES = 64 << 20, 64


def _narrow(df: DataFrame, column: str) -> bool:
    """Whether values of the column have a bounded size."""
    return df.schema[column].dataType.simpleString().split("(")[0] in ("boolean", "tinyint", "smallint", "int", "bigint", "float", "double", "decimal", "date", "timestamp", "timestamp_ntz")


def greedy_full(df: DataFrame, attrs: list[str], exclude: list[str] | None = None, must_include: list[str] | None = None) -> Key:
    """Greedy on all rows by refinement: the next attribute leaves the fewest pairs together; ties go to the order of ``attrs``. Rows carry the id of
    their class; a round scores the attributes that are left on the rows that still share a class, then splits the classes and drops what is alone.
    Pairs are never formed, and after the first rounds few rows are left."""
    forced, rest = _candidates(attrs, exclude, must_include)
    key = Key([])
    live = df.select(F.lit(0).cast("long").alias(_CLASS), *dict.fromkeys([*forced, *rest]))
    gamma = bounds.pairs_of(df.count())
    while gamma:
        names = forced[:1] or rest
        if not names:
            break
        scores = {r.attr: int(r.gamma) for r in score_round(live, names).collect()}  # one row for each attribute
        pick = min(names, key=lambda a: scores[a])
        if scores[pick] == gamma and not forced:
            break
        forced, rest = forced[1:], [a for a in rest if a != pick]
        gamma = scores[pick]
        key.attrs.append(pick)
        key.steps.append((pick, gamma))
        if gamma and (forced or rest):
            live = split_classes(live, pick)
    key.attrs += forced
    key.residual = gamma
    return key


def minimum_key(df: DataFrame, attrs: list[str], largest: int) -> list[str] | None:
    """A true key of the fewest attributes, the first in order; None if there is none of at most ``largest``."""
    for size in range(1, min(largest, len(attrs)) + 1):
        level = list(combinations(attrs, size))
        counted = exact.unseparated_many(df, [(str(i), list(c)) for i, c in enumerate(level)])
        hit = counted.where("gamma = 0").agg(F.min(F.col("set_name").cast("int"))).first()[0]
        if hit is not None:
            return list(level[hit])
    return None


# -- on samples


def refine_greedy(codes: dict[str, np.ndarray], attrs: list[str], exclude: list[str] | None = None, must_include: list[str] | None = None) -> Key:
    """Greedy on a sample of tuples by refining groups of integer codes. Rows that are alone leave; a round costs rows times attributes."""
    forced, rest = _candidates(attrs, exclude, must_include)
    n = len(next(iter(codes.values()), ()))
    rows, group, gamma, key = np.arange(n), np.zeros(n, np.int64), bounds.pairs_of(n), Key([])
    while gamma:
        names = forced[:1] or rest
        if not names:
            break
        best = None
        for a in names:
            code = codes[a][rows]
            # sizes of the refined groups, by sorting (group, code) as one integer
            joint = np.sort(group * (int(code.max(initial=0)) + 1) + code)
            edges = np.flatnonzero(np.concatenate([[True], joint[1:] != joint[:-1], [True]]))
            size = np.diff(edges)
            g = int((size * (size - 1) // 2).sum())
            if best is None or g < best[0]:
                best = (g, a)
        if best[0] == gamma and not forced:
            break
        gamma, pick = best
        forced, rest = forced[1:], [a for a in rest if a != pick]
        group = filters.refine(group, codes[pick][rows])
        left = np.bincount(group)[group] > 1
        rows, group = rows[left], group[left]
        key.attrs.append(pick)
        key.steps.append((pick, gamma))
    key.attrs += forced
    key.residual = gamma
    return key


def mask_greedy(differs: np.ndarray, attrs: list[str], exclude: list[str] | None = None, must_include: list[str] | None = None) -> Key:
    """Greedy on a sample of pairs: rows of ``differs`` are pairs, columns attributes."""
    forced, rest = _candidates(attrs, exclude, must_include)
    at = {a: i for i, a in enumerate(attrs)}
    left, key = differs, Key([])
    while len(left):
        names = forced[:1] or rest
        if not names:
            break
        counts = left.sum(axis=0)
        pick = max(names, key=lambda a: counts[at[a]])
        if counts[at[pick]] == 0 and not forced:
            break
        forced, rest = forced[1:], [a for a in rest if a != pick]
        left = left[~left[:, at[pick]]]
        key.attrs.append(pick)
        key.steps.append((pick, len(left)))
    key.attrs += forced
    key.residual = len(left)
    return key


def exhaustive(accepts, attrs: list[str], upper: int, exclude: list[str] | None = None, must_include: list[str] | None = None) -> list[str] | None:
    """The first smallest set that ``accepts`` takes, of fewer than ``upper`` attributes."""
    forced, rest = _candidates(attrs, exclude, must_include)
    for size in range(max(0, 1 - len(forced)), upper - len(forced)):
        for more in combinations(rest, size):
            if accepts([*forced, *more]):
                return [*forced, *more]
    return None


def find_key(df: DataFrame, eps: float, seed: int, identity: list[Column], attrs: list[str] | None = None, method: str = "tuple_greedy", exclude: list[str] | None = None, must_include: list[str] | None = None, largest: int = 4, **planner) -> Key:
    """A small eps-separation key. tuple_greedy and tuple_exact cover the pairs of a tuple sample, pair_greedy and pair_exact a pair sample; full_greedy and
    full_exact all rows. The exact ones are no larger than the greedy ones."""
    attrs = attrs or df.columns
    if method == "full_greedy":
        return greedy_full(df, attrs, exclude, must_include)
    if method == "full_exact":
        found = minimum_key(df, [a for a in attrs if a not in (exclude or [])], largest)
        return Key(found or [], residual=0 if found else -1)
    if method in ("tuple_greedy", "tuple_exact"):
        kept = filters.TupleFilter.build(df, eps, seed, identity, attrs, **planner)
        key = refine_greedy(kept.codes(), attrs, exclude, must_include)
        if method == "tuple_exact" and key.complete:
            better = exhaustive(kept.accepts, attrs, len(key.attrs), exclude, must_include)
            return Key(better) if better is not None else key
        return key
    if method in ("pair_greedy", "pair_exact"):
        kept = filters.PairFilter.build(df, eps, seed, identity, attrs, **planner)
        key = mask_greedy(~kept.matrix(), attrs, exclude, must_include)
        if method == "pair_exact" and key.complete:
            allowed = [a for a in attrs if a not in (exclude or [])]
            keep = filters.mask_of(allowed, attrs)
            forced = filters.mask_of(must_include or [], attrs)
            masks = filters.minimal_masks([m & keep for m in kept.minimal_masks() if not m & forced])
            found = setcover.exact_cover(masks, len(attrs))
            return Key([*(must_include or []), *[attrs[i] for i in found]])
        return key
    raise ValueError(method)


def validate(df: DataFrame, attrs: list[str], eps: float) -> DataFrame:
    """The found set on all rows: gamma, ratio and verdict."""
    return exact.verdict(df, attrs, eps)
