"""Groups from links that are tested only where two nodes share a bucket.

``link`` takes rows of buckets and nodes and a test of node pairs, and gives every node that has a link the smallest node it reaches. It
loses no link between two nodes that share a bucket, yet does not test all pairs of a large bucket:

1. In buckets of at most ``SMALL`` nodes all pairs are tested; in larger ones each node against one of them, in up to ``STARS`` rounds against
   another each, as long as the bucket's nodes lie in several groups.
2. Where the nodes of a large bucket still lie in several groups, all pairs across groups are looked at, which is what is left for
   completeness: pairs inside a group cannot change it. One pair of each two groups is tested first, then the rest. The caller may find
   these pairs in blocks of bounded size that give out only pairs close to a link.

Bucket sizes come from a pre-aggregate, pairs from equi-joins that AQE may split, groups from star contractions; nothing is gathered in one
task or on the driver.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

SMALL = 3


def _forest(batches):
    """Union-find over one partition's edges: (node, smallest node it reaches) for every node but the smallest."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (up := parent.setdefault(top, top)) != top:
            top = up
        while parent[x] != top:
            parent[x], x = top, parent[x]
        return top

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)
        if len(parent) > 1_000_000:  # hand on what is known and forget it: memory stays bounded
            yield _rows(parent, root)
            parent.clear()
    yield _rows(parent, root)


def _rows(parent, root):
    pairs = [(x, r) for x in list(parent) if (r := root(x)) != x]
    return pa.RecordBatch.from_arrays([pa.array([p[i] for p in pairs], pa.int64()) for i in (0, 1)], ["a", "b"])


#: Edges that a task contracts by itself.
FOREST_EDGES = 400_000


def _state(pairs: DataFrame) -> tuple:
    return tuple(pairs.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, native: bool = False) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b: longs). Each partition first contracts its own edges by union-find (left out where
    ``native``); then large-star and small-star contractions run until nothing moves."""
    pairs = edges.select("a", "b").where("a <> b")
    if not native:
        # parts of like size, so that few edges are contracted in few parts
        pairs = common.map_arrow(pairs.coalesce(1 + pairs.count() // FOREST_EDGES), _forest, "a long, b long")
    pairs = common.durable(pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    seen = _state(pairs)
    while True:
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        # large star: each larger neighbour goes to the smallest node around
        pairs = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # small star: all smaller neighbours, and the node, go to the smallest of them
        least = pairs.groupBy("a").agg(F.min("b").alias("m"))
        moved = pairs.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        pairs = common.durable(least.select("a", F.col("m").alias("b")).unionByName(moved).distinct(), "edges")
        state = _state(pairs)
        if state == seen:
            break
        seen = state
    return pairs.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(pairs.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


#: Nodes of a side of a block when all pairs of a large bucket are looked at.
BLOCK = 256


def _sides():
    """For ``may``: gives a node's columns by name, for the left and the right node of a pair."""
    return (lambda c: F.col(c)), (lambda c: F.col(f"other_{c}"))


def _other(df: DataFrame, keep: list[str]) -> DataFrame:
    return df.select(*keep, *[F.col(c).alias(f"other_{c}") for c in df.columns if c not in keep])


def link(members: DataFrame, test: Callable[[DataFrame], DataFrame], may: Callable[[Callable, Callable], Column], across: Callable[[DataFrame], DataFrame] | None = None, native: bool = False) -> tuple[DataFrame, DataFrame]:
    """members: bucket, node and columns that depend on both. ``may(left, right)`` is a cheap necessary condition over these columns of two
    nodes; ``test`` keeps the linked of pairs (a, b), a < b. ``across`` takes the rows (of members, with size and root) of the buckets whose nodes
    lie in several groups, and gives the pairs of a bucket, in different groups, that may be linked; without it, those that satisfy ``may``.
    ``native`` leaves Python out of the executors.

    Gives (node, root) of all linked nodes, and the links found."""
    left, right = _sides()
    payload = [c for c in members.columns if c not in ("bucket", "node")]
    # most buckets hold one node: they go before anything else is moved
    shared = common.durable(members.groupBy("bucket").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("bucket"), "shared")
    live = members.join(common.small(shared, F.lit(24)), "bucket", "left_semi").groupBy("bucket", "node").agg(*[F.min(c).alias(c) for c in payload])
    live = common.durable(live, "members")
    sizes = live.groupBy("bucket").agg(F.count("*").alias("size"))
    live = common.durable(live.join(sizes, "bucket"), "buckets")
    few = live.where(F.col("size") <= SMALL).select("bucket", "node", *payload)
    pairs = few.join(_other(few, ["bucket"]), "bucket").where((F.col("node") < F.col("other_node")) & may(left, right)).select(F.col("node").alias("a"), F.col("other_node").alias("b"))
    many = live.where(F.col("size") > SMALL)
    found = Links(test, native)
    spots = many.withColumn("root", F.col("node"))
    for k in range(1 if across else STARS):
        # in each bucket another node, the same for buckets of the same nodes
        lead = spots.groupBy("bucket").agg(F.min(F.struct(F.xxhash64("node", F.lit(k)), F.struct("node", "root", *payload).alias("n"))).alias("x")).select("bucket", "x.n.*")
        stars = spots.join(_other(lead, ["bucket"]), "bucket").where((F.col("root") != F.col("other_root")) & may(left, right))
        stars = stars.select(F.least("node", "other_node").alias("a"), F.greatest("node", "other_node").alias("b"))
        if not found.add(stars if k else pairs.unionByName(stars)) and k:
            break
        spots = found.across(many)
        if spots.isEmpty():
            return found.roots, found.links
    # what is left: all pairs across groups; where nothing but ``may`` has chosen them, first one pair of each two groups
    if across:
        found.add(across(spots))
        return found.roots, found.links
    rest = common.durable(_blocks(spots, may).distinct(), "rest")
    rooted = found.rooted(rest)
    found.add(rooted.groupBy("root_a", "root_b").agg(F.min(F.struct(F.xxhash64("a", "b"), "a", "b")).alias("x")).select("x.a", "x.b"))
    found.add(found.rooted(rest).select("a", "b"))
    return found.roots, found.links


#: Rounds in which each open bucket's nodes are tested against one of them (one round where ``across`` finds the rest).
STARS = 1


class Links:
    """Tested pairs, links and groups so far."""

    def __init__(self, test: Callable[[DataFrame], DataFrame], native: bool = False):
        self.test, self.native, self.tested, self.links, self.roots = test, native, None, None, None

    def add(self, pairs: DataFrame) -> bool:
        """Tests the pairs that have not been tested; whether there were any."""
        pairs = pairs.distinct()
        new = common.durable(pairs if self.tested is None else pairs.join(self.tested, ["a", "b"], "left_anti"), "pairs")
        if self.tested is not None and new.isEmpty():
            return False
        self.tested = new if self.tested is None else self.tested.unionByName(new)
        more = common.durable(self.test(new), "links")
        known = more if self.roots is None else more.unionByName(self.roots.select(F.col("node").alias("a"), F.col("root").alias("b")))
        self.links = more if self.links is None else self.links.unionByName(more)
        if self.roots is None or not more.isEmpty():
            self.roots = common.durable(components(known, self.native), "roots")
        return True

    def across(self, many: DataFrame) -> DataFrame:
        """The rows of the buckets whose nodes lie in several groups, with their groups."""
        spots = many.join(self.roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
        split = spots.groupBy("bucket").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("bucket")
        return common.durable(spots.join(split, "bucket", "left_semi"), "open")

    def rooted(self, pairs: DataFrame) -> DataFrame:
        """a, b, root_a < root_b of the pairs whose nodes lie in two groups."""
        root = lambda c: self.roots.select(F.col("node").alias(c), F.col("root").alias(f"root_{c}"))
        both = pairs.join(root("a"), "a", "left").join(root("b"), "b", "left").select("a", "b", F.coalesce("root_a", "a").alias("p"), F.coalesce("root_b", "b").alias("q"))
        return both.where("p <> q").select("a", "b", F.least("p", "q").alias("root_a"), F.greatest("p", "q").alias("root_b"))


def _blocks(spots: DataFrame, may) -> DataFrame:
    """All pairs of a bucket, in different groups, that satisfy ``may``. A bucket's nodes are dealt to sides of about BLOCK; each two sides are a
    key of their own, so that no bucket is one task's."""
    left, right = _sides()
    sides = F.ceil(F.col("size") / BLOCK).cast("int")
    spots = spots.withColumn("side", F.pmod(F.xxhash64("node"), sides).cast("int")).withColumn("sides", sides)
    here = spots.select("*", F.col("side").alias("i"), F.explode(F.sequence("side", F.col("sides") - 1)).alias("j"))
    there = spots.select("*", F.explode(F.sequence(F.lit(0), "side")).alias("i"), F.col("side").alias("j"))
    both = here.join(_other(there, ["bucket", "i", "j"]), ["bucket", "i", "j"])
    both = both.where(((F.col("i") < F.col("j")) | (F.col("node") < F.col("other_node"))) & (F.col("root") != F.col("other_root")) & may(left, right))
    return both.select(F.least("node", "other_node").alias("a"), F.greatest("node", "other_node").alias("b"))
