"""Exact counts of many sets by few shuffles: the rows are dealt by one attribute, and every set that holds it is counted inside the parts.

Rows equal on a set are equal on each of its attributes, so that all groups of all sets with the dealt attribute lie within its parts. A part is counted on
integer codes, exactly: codes of a set's attributes are joined in mixed radix and made dense again before they pass 64 bits. Rows that are alone in a set are
alone in every larger one, and leave it.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sepkey.sources import stores

#: About the rows of a part, and the most that one may have: attributes whose parts would be larger are not dealt by.
PART_ROWS, MOST_ROWS = 250_000, 1_000_000
#: Joined codes stay below this.
_SPAN = 1 << 62
_COUNTS = "set_id long, n long, gamma long, groups long, max_group long"


def plain(kind: T.DataType) -> bool:
    return isinstance(kind, (T.IntegralType, T.FractionalType, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType))


def key_of(df: DataFrame, attr: str):
    """What rows are dealt by: equal where Spark groups values together."""
    from sepkey.operators import exact

    return exact.canonical(F.col(attr), df.schema[attr].dataType)


def largest_parts(df: DataFrame, attrs: list[str], parts: int) -> dict[str, int]:
    """The rows of the largest part for each attribute, counted in one pass: parts * attributes counters."""
    place = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.pmod(F.hash(key_of(df, a)), F.lit(parts)).alias("p")) for i, a in enumerate(attrs)])).alias("x")
    got = df.select(place).select("x.*").groupBy("i", "p").agg(F.count("*").alias("k")).groupBy("i").agg(F.max("k").alias("k")).collect()  # one row an attribute
    return {attrs[r.i]: r.k for r in got}


#: Fewer sets than these are not worth a shuffle of uneven parts.
_WORTH = 3


def plan(sets: list[tuple[str, ...]], even: dict[str, int], uneven: dict[str, int]) -> tuple[list[tuple[str, list[int]]], list[int]]:
    """(attribute, numbers of the sets counted by it), and the numbers of the sets that are left: the attribute in most of the sets not yet counted goes
    first, of those with even parts before the others."""
    left, out = list(range(len(sets))), []
    for allowed, worth in ((even, 1), (uneven, _WORTH)):
        while True:
            held = {a: [i for i in left if a in sets[i]] for a in allowed}
            best = max(held, key=lambda a: (len(held[a]), -allowed[a]), default=None)
            if best is None or len(held[best]) < worth:
                break
            out.append((best, held[best]))
            left = [i for i in left if best not in sets[i]]
    return out, left


def counts(df: DataFrame, sets: list[tuple[str, ...]], n: int) -> tuple[dict[int, tuple], list[int]]:
    """Set number to (n, gamma, groups, max_group), and the numbers of the sets that have to be counted otherwise."""
    used = list(dict.fromkeys(a for attrs in sets for a in attrs if plain(df.schema[a].dataType)))
    parts = max(df.sparkSession.sparkContext.defaultParallelism, math.ceil(n / PART_ROWS))
    sizes = largest_parts(df, used, parts) if used else {}
    fits = {a: k for a, k in sizes.items() if k <= MOST_ROWS}
    even = {a: k for a, k in fits.items() if k * parts <= 2 * n}
    steps, rest = plan(sets, even, {a: k for a, k in fits.items() if a not in even})
    found = {}
    for attr, numbers in steps:
        columns = list(dict.fromkeys([attr, *[a for i in numbers for a in sets[i]]]))
        rows = df.select(*[F.col(a) for a in columns]).repartition(parts, key_of(df, attr)).toDF(*[f"c{i}" for i in range(len(columns))])
        inside = [(i, [columns.index(a) for a in sets[i]]) for i in numbers]
        each = stores.map_arrow(rows, _counter(inside), _COUNTS)
        total = each.groupBy("set_id").agg(F.sum("n").alias("n"), F.sum(F.col("gamma").cast("decimal(38,0)")).cast("decimal(38,0)").alias("gamma"), F.sum("groups").alias("groups"), F.max("max_group").alias("max_group"))
        found |= {r.set_id: (r.n, r.gamma, r.groups, r.max_group) for r in total.collect()}  # one row a set
    return found, rest


def _counter(sets: list[tuple[int, list[int]]]):
    def run(batches):
        from sepkey.operators.filters import codes_of

        batches = [b for b in batches if b.num_rows]
        if not batches:
            return
        rows = pa.Table.from_batches(batches)
        del batches
        code = list(codes_of(rows).values())
        out = count_codes(code, rows.num_rows, sets)
        yield pa.RecordBatch.from_arrays([pa.array(list(x), pa.int64()) for x in zip(*out, strict=True)], [c.split()[0] for c in _COUNTS.split(", ")])

    return run


def count_codes(code: list[np.ndarray], n: int, sets: list[tuple[int, list[int]]]) -> list[tuple[int, int, int, int, int]]:
    """(number, n, gamma, groups, max_group) of each set of columns, smaller sets first."""
    radix = [int(c.max(initial=0)) + 1 for c in code]
    alive: list[tuple[frozenset, np.ndarray]] = []  # sets that few rows share, and those rows
    out = []
    for number, columns in sorted(sets, key=lambda x: len(x[1])):
        mine = frozenset(columns)
        rows = min((r for s, r in alive if s <= mine), key=len, default=None)
        joint = np.sort(whole := _joined(code, radix, sorted(mine, key=lambda c: radix[c]), n if rows is None else len(rows), rows))
        edges = np.flatnonzero(np.concatenate([[True], joint[1:] != joint[:-1], [True]])) if len(joint) else np.zeros(1, np.int64)
        size = np.diff(edges)
        shared = joint[edges[:-1][size > 1]]
        out.append((number, n, int((size * (size - 1) // 2).sum()), len(size) + n - len(joint), int(size.max(initial=1))))
        if len(shared) * 8 <= len(joint):
            at = np.searchsorted(shared, whole)
            kept = np.flatnonzero(shared[np.minimum(at, len(shared) - 1)] == whole) if len(shared) else np.zeros(0, np.int64)
            if len(kept) * 2 <= n and (rows is None or len(kept) < len(rows)):
                alive.append((mine, kept if rows is None else rows[kept]))
    return out


def _joined(code: list[np.ndarray], radix: list[int], columns: list[int], n: int, rows: np.ndarray | None) -> np.ndarray:
    joint, span = np.zeros(n, np.int64), 1
    for c in columns:
        if span * radix[c] >= _SPAN:
            joint = np.unique(joint, return_inverse=True)[1]
            span = int(joint.max(initial=0)) + 1
        joint = joint * radix[c] + (code[c] if rows is None else code[c][rows])
        span *= radix[c]
    return joint
