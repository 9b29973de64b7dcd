"""Measures: agreement, contract violations, failure rates, size ratios, errors, and the timed comparison of both filters."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sepkey.functions import bounds
from sepkey.operators import exact, filters, mincover, nonsep, sampling
from sepkey.sources.stores import durable

Sets = list[tuple[str, list[str]]]


def agreement(answers: DataFrame) -> DataFrame:
    """sets, agree, only_pairs_accept, from set_name, tuple_accept, pair_accept."""
    same = F.col("tuple_accept") == F.col("pair_accept")
    return answers.agg(F.count("*").alias("sets"), F.count_if(same).alias("agree"), F.count_if(F.col("pair_accept") & ~F.col("tuple_accept")).alias("only_pairs_accept"))


def confusion(answers: DataFrame, truth: DataFrame) -> DataFrame:
    return answers.join(truth, "set_name").groupBy("verdict", "tuple_accept", "pair_accept").agg(F.count("*").alias("sets"))


def violations(table: DataFrame) -> DataFrame:
    """Keys rejected (never, by construction) and bad sets accepted, of each filter, from ``confusion``."""
    count = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("sets"))), F.lit(0)).cast("long")
    key, bad = F.col("verdict") == "key", F.col("verdict") == "bad"
    return table.agg(count(key & ~F.col("tuple_accept")).alias("tuple_rejects_key"), count(bad & F.col("tuple_accept")).alias("tuple_accepts_bad"), count(key & ~F.col("pair_accept")).alias("pair_rejects_key"), count(bad & F.col("pair_accept")).alias("pair_accepts_bad"))


def wrong(answers: dict[str, bool], truth: dict[str, str]) -> int:
    return sum((truth[n] == "key" and not a) or (truth[n] == "bad" and a) for n, a in answers.items())


def failure_trials(spark: SparkSession, df: DataFrame, sets: Sets, truth: dict[str, str], eps: float, identity: list[Column], attrs: list[str], seeds) -> DataFrame:
    """method, trials, failed (trials with a wrong answer: the for-all notion), wrong (answers, over all trials: the for-each notion). Ordinals are
    numbered once for all trials."""
    rows = durable(sampling.ordinals(df.select("*"), identity), "ordinals")
    n = rows.count()
    found = {"tuples": [], "pairs": []}
    for seed in seeds:
        found["tuples"].append(wrong(filters.TupleFilter.build(df, eps, seed, identity, attrs).query_many(sets), truth))
        found["pairs"].append(wrong(filters.PairFilter.build(df, eps, seed, identity, attrs, rows=rows, n=n).query_many(sets), truth))
    return spark.createDataFrame([(k, len(v), sum(x > 0 for x in v), sum(v)) for k, v in found.items()], "method string, trials long, failed long, wrong long")


def sensitivity(spark: SparkSession, df: DataFrame, sets: Sets, identity: list[Column], attrs: list[str], seed: int) -> DataFrame:
    """inverse_eps, factor_percent, tuples, bad_sets, accepted_bad: how misses move with the sample's size. A smaller sample of the
    same seed is the part of a larger one with the least ranks: the table is read for the largest alone."""
    counted = exact.unseparated_many(df, sets).collect()
    gamma, n = {r.set_name: int(r.gamma) for r in counted}, counted[0].n
    most = max(bounds.tuple_sample_size(len(attrs), eps, c=c) for eps in (0.1, 0.01, 0.001) for c in (0.25, 0.5, 1.0, 2.0, 4.0))
    top = durable(sampling.tuples(df, most, seed, identity, n=n), "top")
    out = []
    for eps in (0.1, 0.01, 0.001):
        bad = {s for s, g in gamma.items() if g > eps * bounds.pairs_of(n)}
        for c in (0.25, 0.5, 1.0, 2.0, 4.0):
            kept = filters.TupleFilter.build(top, eps, seed, identity, attrs, c=c)
            answers = kept.query_many(sets)
            out.append((round(1 / eps), round(100 * c), kept.about["r"], len(bad), sum(answers[s] for s in bad)))
    return spark.createDataFrame(out, "inverse_eps long, factor_percent long, tuples long, bad_sets long, accepted_bad long")


def size_ratios(spark: SparkSession, tables: list[tuple], eps: float, seed: int) -> DataFrame:
    """For each table: sizes of the greedy keys from tuples and from pairs, of the greedy key of all rows, and of the true minimum; what the found one
    leaves together, in parts per billion."""
    out = []
    for name, df, identity, attrs in tables:
        tuple_key = mincover.find_key(df, eps, seed, identity, attrs)
        pair_key = mincover.find_key(df, eps, seed, identity, attrs, method="pair_greedy")
        full = mincover.greedy_full(df, attrs)
        least = mincover.minimum_key(df, attrs, len(full.attrs)) or []
        left = exact.unseparated(df, tuple_key.attrs).first()
        together = math.floor(float(left.gamma) / float(bounds.pairs_of(left.n)) * 1e9) if left.n > 1 else 0
        out.append((name, len(tuple_key.attrs), len(pair_key.attrs), len(full.attrs), len(least), together))
    return spark.createDataFrame(out, "name string, tuple_greedy long, pair_greedy long, full_greedy long, minimum long, together_ppb long")


def sketch_sweep(spark: SparkSession, df: DataFrame, identity: list[Column], attrs: list[str], seed: int) -> DataFrame:
    """k, alpha, eps: pairs of the sketch, sets of at most k attributes, those above alpha, the largest error among them, and broken guarantees."""
    rows = durable(sampling.ordinals(df.select("*"), identity), "ordinals")
    n = rows.count()
    largest = nonsep.PairSketch.build(df, 3, 0.01, 0.1, seed, identity, attrs, rows=rows, n=n)  # the others are its first pairs
    truth = durable(exact.unseparated_many(df, [(",".join(s), s) for s in _up_to(attrs, 3)]), "truth")
    out = []
    for k in (1, 2, 3):
        sets = [(",".join(s), s) for s in _up_to(attrs, k)]
        for alpha in (0.1, 0.01):
            for eps in (0.1, 0.2):
                sketch = largest.first(k, alpha, eps)
                z = nonsep.zones(sketch.estimate_many(sets), truth, alpha, eps)
                got = z.agg(F.count_if(F.col("zone") == "high").alias("high"), F.max(F.when(F.col("zone") == "high", F.abs("relative_error"))).alias("worst"), F.count_if(~F.col("holds")).alias("broken")).first()
                out.append((k, round(1 / alpha), round(1 / eps), sketch.about["s"], len(sets), got.high, int((got.worst or 0) * 1e6), got.broken))
    return spark.createDataFrame(out, "k long, inverse_alpha long, inverse_eps long, pairs long, sets long, high_sets long, worst_error_ppm long, broken long")


def _up_to(attrs: list[str], k: int) -> list[list[str]]:
    from itertools import combinations

    return [list(c) for size in range(1, k + 1) for c in combinations(attrs, size)]


def bounds_table(tables: dict[str, DataFrame], eps: float = 0.001) -> DataFrame:
    """The remaining bounds of each table as named values (parts per million of a natural logarithm, or of a number): m is its number of columns; its
    rows, and the largest group of any single column, are counted."""
    micro = lambda x: int(round(x * 1e6)) if x > -math.inf else None
    out = []
    for table, df in tables.items():
        m, counted = len(df.columns), exact.unseparated_many(df, [(c, [c]) for c in df.columns]).agg(F.max("n").alias("n"), F.max("max_group").alias("top")).first()
        n, r = counted.n or 0, bounds.tuple_sample_size(m, eps)
        heaviest = (counted.top or 0) / max(1, n)
        regime = bounds.check_regime(n, m, r, eps)
        out += [(table, k, r, micro(float(v))) for k, v in regime.items()]
        out += [(table, "heaviest_group", n, micro(heaviest)), (table, "heaviest_group_missed", r, micro(bounds.log_two_valued(r, heaviest, 1, 1 - heaviest)) if n else None)]
        out += [(table, "worst_profile_true_eps", m, micro(bounds.worst_profile(r, eps)["log_miss"])), (table, "worst_profile_relaxed_eps", m, micro(bounds.worst_profile(r, eps, True)["log_miss"]))]
        out += [(table, "union_per_set", m, micro(bounds.final_union(m)["per_set"])), (table, "union_all_sets", m, micro(bounds.final_union(m)["all_sets"]))]
        out += [(table, "constant_failure_tuples", m, micro(bounds.constant_failure_tuples(m, eps)))]
        out += [(table, "two_groups_expected_draws", m, micro(bounds.group_argument(4, eps, m)["expected"]))]
        out += [(table, "sketch_bits_lower", m, micro(bounds.sketch_bits_lower(m, 2, 0.1))), (table, "sketch_bits_upper", m, micro(bounds.sketch_bits_upper(m, 2, 0.01, 0.1)))]
        out += [(table, "heavy_profile", r, micro(bounds.compare_profiles(r, eps)["heavy"])), (table, "equal_profile_possible", r, 1_000_000 * int(bounds.compare_profiles(r, eps)["equal"] > -math.inf))]
        out += [(table, "counting_failure", t, micro(bounds.counting_bound(3, m, t)["failure"])) for t in (3, 5)]
    return next(iter(tables.values())).sparkSession.createDataFrame(out, "table string, name string, parameter long, value_micro long")


def timed(build, query) -> tuple[float, float, object]:
    """Seconds to build and to query, and the answers."""
    a = time.perf_counter()
    kept = build()
    b = time.perf_counter()
    answers = query(kept)
    return b - a, time.perf_counter() - b, (kept, answers)


def compare(sets: Sets, trials: int, tuples, pairs) -> dict:
    """Sample sizes, mean build and query seconds of both filters over ``trials`` seeds, the mean agreement, and what follows: how many times fewer
    tuples than pairs, and how many times faster. ``tuples`` and ``pairs`` build a filter from a seed, from the table itself: whatever they need to
    draw their samples is on their clock."""
    out = {"tuples": {"build": 0.0, "query": 0.0}, "pairs": {"build": 0.0, "query": 0.0}, "agree": 0.0, "only_pairs_accept": 0.0, "trials": trials}
    for seed in range(trials):
        got = {}
        for name, make in (("tuples", tuples), ("pairs", pairs)):
            build, query, (kept, answers) = timed(lambda m=make, s=seed: _loaded(m(s)), lambda k: k.query_many(sets))
            out[name]["build"] += build / trials
            out[name]["query"] += query / trials
            out[name]["size"] = kept.about.get("r", kept.about.get("s"))
            got[name] = answers
        out["agree"] += sum(got["tuples"][n] == got["pairs"][n] for n, _ in sets) / len(sets) / trials
        out["only_pairs_accept"] += sum(got["pairs"][n] and not got["tuples"][n] for n, _ in sets) / len(sets) / trials
    seconds = {k: out[k]["build"] + out[k]["query"] for k in ("tuples", "pairs")}
    return out | {"reduction": out["pairs"]["size"] / out["tuples"]["size"], "speed_up": seconds["pairs"] / seconds["tuples"]}


def _loaded(kept):
    """Sampling is lazy in Spark: loading the codes is part of building."""
    if isinstance(kept, filters.TupleFilter):
        kept.codes()
    else:
        kept.packed()
    return kept
