"""Set cover over element-set rows: greedy in Spark, exact on bit masks."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sepkey.sources.stores import durable


#: Most rows (element, set) still uncovered that the driver takes to finish alone.
DRIVER_ROWS = 200_000


def greedy(instance: DataFrame) -> list[tuple[str, int]]:
    """instance: elem, name. Chosen sets and how many new elements each covers, within ln N + 1 of the optimum; ties go to the smallest name. Elements
    of chosen sets leave by an anti-join, so a round costs what is still uncovered; once that is at most DRIVER_ROWS rows, the driver takes the
    remaining rounds in the same order."""
    left, out = durable(instance.select("elem", "name").distinct(), "cover"), []
    while left.count() > DRIVER_ROWS:
        best = left.groupBy("name").agg(F.count("*").alias("c")).orderBy(F.desc("c"), "name").first()
        out.append((best["name"], best["c"]))
        done = left.where(F.col("name") == best["name"]).select("elem")
        left = durable(left.join(done, "elem", "left_anti"), "cover")
    sets: dict[str, set] = {}
    for r in left.collect():
        sets.setdefault(r["name"], set()).add(r["elem"])
    return out + _greedy_sets(sets)


def _greedy_sets(sets: dict[str, set]) -> list[tuple[str, int]]:
    """A count on the heap can only be too large; the first that is still right is the largest, and of equal ones the smallest name."""
    heap, covered, out = [(-len(e), n) for n, e in sets.items()], set(), []
    heapq.heapify(heap)
    while heap:
        c, n = heapq.heappop(heap)
        sets[n] -= covered
        if len(sets[n]) == -c:
            out.append((n, -c))
            covered |= sets[n]
        elif sets[n]:
            heapq.heappush(heap, (-len(sets[n]), n))
    return out


def exact_cover(masks: list[int], width: int) -> list[int] | None:
    """The fewest of ``width`` sets that meet every mask (bit i: set i covers the element); None if a mask is empty. Branches on the mask with the
    fewest sets; a branch ends where the sets so far and the masks that are still pairwise disjoint cannot beat the best."""
    if any(m == 0 for m in masks):
        return None
    best = greedy_masks(masks)

    def search(left: list[int], chosen: list[int]) -> None:
        nonlocal best
        if not left:
            if len(chosen) < len(best):
                best = sorted(chosen)
            return
        need, used = 0, 0
        for m in sorted(left, key=int.bit_count):
            if not m & used:
                used |= m
                need += 1
        if len(chosen) + need >= len(best):
            return
        pick = min(left, key=lambda m: (m.bit_count(), m))
        for i in range(width):
            if pick >> i & 1:
                search([m for m in left if not m >> i & 1], [*chosen, i])

    search(sorted(set(masks)), [])
    return sorted(best)


def greedy_masks(masks: list[int]) -> list[int]:
    left, out = list(masks), []
    while left:
        counts: dict[int, int] = {}
        for m in left:
            while m:
                low = m & -m
                counts[low.bit_length() - 1] = counts.get(low.bit_length() - 1, 0) + 1
                m ^= low
        pick = min(counts, key=lambda i: (-counts[i], i))
        out.append(pick)
        left = [m for m in left if not m >> pick & 1]
    return out
