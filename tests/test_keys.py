from __future__ import annotations

import datetime
import decimal
import math
import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from sepkey.functions import bounds
from sepkey.operators import exact, filters, hardness, mincover, nonsep, relational, sampling, setcover
from sepkey.plans import catalog
from sepkey.sources import stores
from sepkey.sources.stores import table
from tests.paths import SMALL

ROWS = [(1, "a", None, 1.0), (2, "a", None, -0.0), (3, "b", None, 0.0), (4, "b", "x", float("nan")), (5, "b", "x", float("nan")), (6, None, "y", 2.0)]
KIND = "id long, p string, q string, r double"


def gamma(df, attrs, **kw):
    return int(exact.unseparated(df, attrs, **kw).first().gamma)


def test_groups_treat_nulls_zeros_and_nans_as_values(spark):
    df = spark.createDataFrame(ROWS, KIND)
    assert gamma(df, ["p"]) == 1 + 3
    assert gamma(df, ["q"]) == 3 + 1
    assert gamma(df, ["q"], null_mode="distinct") == 1
    assert gamma(df, ["r"]) == 2
    assert gamma(df, []) == 15
    sets = [("p", ["p"]), ("q", ["q"]), ("r", ["r"]), ("pq", ["p", "q"]), ("id", ["id"])]
    for strategy in ("fingerprint", "grouping_sets", "lattice"):
        got = {r.set_name: int(r.gamma) for r in exact.unseparated_many(df, sets, strategy).collect()}
        assert got == {"p": 4, "q": 4, "r": 2, "pq": 2, "id": 0}, strategy


def test_empty_and_single_row_tables(spark):
    for n, want in ((0, 0), (1, 1)):
        df = spark.createDataFrame(ROWS[:n], KIND)
        row = exact.unseparated(df, ["p"]).first()
        assert (row.n, int(row.gamma), row.groups, row.ratio) == (want, 0, want, 1.0)
        assert filters.TupleFilter.build(df, 0.1, 1, [F.col("id")]).accepts(["p"])


def test_duplicates_leave_a_residual(spark):
    df = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b")], "id long, p string").select("p", F.lit(0).alias("q"))
    key = mincover.greedy_full(df, ["p", "q"])
    assert (key.attrs, key.residual, key.complete) == (["p"], 1, False)
    assert mincover.minimum_key(df, ["p", "q"], 2) is None


def test_edges_are_cliques(spark):
    df = table(spark, SMALL, "customer")
    edges = exact.unseparated_edges(df, ["c_mktsegment"], "c_custkey")
    assert edges.count() == gamma(df, ["c_mktsegment"])
    assert exact.open_paths(edges).isEmpty()


def test_map_columns_group_and_variants_fail(spark):
    df = spark.range(4).select(F.create_map(F.lit("k"), F.col("id") % 2).alias("m"))
    assert gamma(df, ["m"]) == 2


def test_separation_is_monotone(spark):
    df = table(spark, SMALL, "part")
    for a, b in combinations(["p_brand", "p_type", "p_size"], 2):
        assert gamma(df, [a, b]) <= min(gamma(df, [a]), gamma(df, [b]))
    row = exact.marginal_gain(df, ["p_size"], "p_brand").first()
    assert int(row.gain) == gamma(df, ["p_size"]) - gamma(df, ["p_size", "p_brand"])


def test_sampler_is_uniform_over_rows_not_contents(spark):
    n, r, trials = 60, 12, 200
    df = spark.range(n).select("id", F.lit("same").alias("p"))
    seen = np.zeros(n)
    for seed in range(trials):
        got = [x.id for x in sampling.tuples(df, r, seed, [F.col("id")]).collect()]
        assert len(got) == len(set(got)) == r
        seen[got] += 1
    p = r / n
    assert np.abs(seen / trials - p).max() < 5 * math.sqrt(p * (1 - p) / trials)


def test_threshold_and_plain_sampling_agree(spark):
    df = table(spark, SMALL, "orders")
    ids = catalog.identity("orders")
    for rank in ("md5", "xxhash64"):
        plain = {r.o_orderkey for r in sampling.tuples(df, 50, 3, ids, rank).collect()}
        assert plain == {r.o_orderkey for r in sampling.tuples(df, 50, 3, ids, rank, n=df.count()).collect()}


def test_plans_hold_no_full_sort(spark):
    df = table(spark, SMALL, "lineitem")
    plan = sampling.tuples(df, 100, 1, catalog.identity("lineitem"))._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in plan and "Exchange" not in plan
    assert "l_shipdate" not in exact.unseparated(df, ["l_partkey"])._jdf.queryExecution().executedPlan().toString()


def test_ordinals_number_rows_by_identity(spark):
    df = table(spark, SMALL, "orders")
    rows = sampling.ordinals(df, catalog.identity("orders")).orderBy("ordinal").select("ordinal", "o_orderkey").collect()
    assert [r.ordinal for r in rows] == list(range(len(rows)))
    assert [r.o_orderkey for r in rows] == sorted(r.o_orderkey for r in rows)
    by_file = sampling.file_ordinals(df).select("ordinal").collect()
    assert sorted(r.ordinal for r in by_file) == list(range(len(rows)))


def test_pairs_are_distinct_rows(spark):
    df = table(spark, SMALL, "customer")
    for mode in ("independent", "disjoint"):
        got = sampling.pairs(df, 60, 5, catalog.identity("customer"), mode).collect()
        assert len(got) == 60 and all(r.l.c_custkey != r.r.c_custkey for r in got)


@pytest.fixture(scope="module")
def lineitem(spark):
    return table(spark, SMALL, "lineitem").cache()


def test_filters_keep_the_contract_over_seeds(spark, lineitem):
    attrs, ids = catalog.attributes("lineitem"), catalog.identity("lineitem")
    sets = catalog.named(catalog.random_sets(attrs, 60) + catalog.random_sets(attrs, 40, seed=7, largest=2))
    truth = {r.set_name: r.verdict for r in exact.unseparated_many(lineitem, sets).select("set_name", exact.verdict_of(F.col("gamma"), F.col("n"), 0.001).alias("verdict")).collect()}
    rows = sampling.ordinals(lineitem, ids).cache()
    for seed in range(10):
        kept = filters.TupleFilter.build(lineitem, 0.001, seed, ids, attrs, mode="calibrated")
        answers = kept.query_many(sets)
        assert answers == {n: kept.accepts(a) for n, a in sets}
        for n, _ in sets:
            assert answers[n] or truth[n] != "key"
            assert not answers[n] or truth[n] != "bad"
    pairs = filters.PairFilter.build(lineitem, 0.001, 1, ids, attrs, rows=rows)
    got = pairs.query_many(sets)
    assert all(got[n] for n, _ in sets if truth[n] == "key")
    assert got == {r.set_name: r.accept for r in pairs.query_df(sets).collect()}
    assert got == {n: all(m & filters.mask_of(a, attrs) for m in pairs.minimal_masks()) for n, a in sets}


def test_ways_to_query_agree_and_samples_are_stored(spark, lineitem, tmp_path):
    attrs, ids = catalog.attributes("lineitem"), catalog.identity("lineitem")
    sets = catalog.named(catalog.SETS["lineitem"])
    kept = filters.TupleFilter.build(lineitem, 0.001, 42, ids, attrs)
    answers = kept.query_many(sets)
    for strategy in ("hash", "sort", "grouping_sets"):
        assert answers == {r.set_name: r.accept for r in kept.query_df(sets, strategy).collect()}
    kept.save(str(tmp_path / "sample"))
    again = filters.TupleFilter.load(spark, str(tmp_path / "sample"))
    assert again.query_many(sets) == answers and again.about["r"] == 348
    assert not kept.about["guaranteed"]  # 6000 rows are too few for 348 tuples
    assert kept.witness(["l_suppkey"], "l_orderkey").count() > 0


def test_a_row_drawn_twice_is_no_collision(spark):
    df = spark.range(40).select("id")
    kept = filters.TupleFilter.build(df, 0.1, 3, [F.col("id")], r=200, replacement=True)
    assert kept.accepts(["id"])


def test_graded_pairs_equal_plain_pairs(spark, lineitem):
    codes = lineitem.select("l_orderkey", "l_extendedprice", F.col("l_partkey").alias("a"), F.col("l_suppkey").cast("long").alias("b")).cache()
    ids = catalog.identity("lineitem")
    moduli = (None, 7, 2)
    names = [f"{c}{m}" for c in ("a", "b") for m in moduli]
    graded = filters.PairFilter.build_graded(codes, 0.01, 5, ids, ["a", "b"], moduli, names, s=500)
    wide = codes.select("l_orderkey", "l_extendedprice", *[(F.col(c) if m is None else F.col(c) % m).alias(f"{c}{m}") for c in ("a", "b") for m in moduli])
    plain = filters.PairFilter.build(wide, 0.01, 5, ids, names, s=500)
    sets = catalog.named(catalog.random_sets(names, 30))
    assert graded.query_many(sets) == plain.query_many(sets)


def test_covers(spark):
    df, attrs = table(spark, SMALL, "supplier"), ["s_nationkey", "s_name", "s_acctbal"]
    pairs = mincover.instance(df, "s_suppkey", attrs)
    assert pairs.count() == bounds.pairs_of(df.count())
    assert mincover.greedy_pairs(pairs, attrs).steps == mincover.greedy_full(df, attrs).steps
    part = table(spark, SMALL, "part")
    names = catalog.ATTRIBUTES["part"][1:]
    greedy = mincover.greedy_full(part, names)
    least = mincover.minimum_key(part, names, 4)
    assert len(least) <= len(greedy.attrs) and exact.is_key(part, least)
    codes = filters.codes_of(part.select(*names).toArrow())
    assert mincover.refine_greedy(codes, names).steps == greedy.steps
    for method in ("tuple_greedy", "tuple_exact", "pair_greedy", "pair_exact"):
        key = mincover.find_key(part, 0.01, 3, catalog.identity("part"), names, method=method)
        assert exact.unseparated(part, key.attrs).first().ratio >= 0.99
    forced = mincover.find_key(part, 0.01, 3, catalog.identity("part"), names, must_include=["p_type"], exclude=["p_retailprice"])
    assert forced.attrs[0] == "p_type" and "p_retailprice" not in forced.attrs


def test_set_cover_bounds(spark):
    rng = np.random.default_rng(2)
    flags = rng.random((40, 12)) < 0.25
    flags[:, 0] |= ~flags.any(axis=1)
    masks = [sum(1 << j for j in np.flatnonzero(r).tolist()) for r in flags]
    best = setcover.exact_cover(masks, 12)
    brute = next(c for k in range(1, 13) for c in combinations(range(12), k) if all(any(m >> i & 1 for i in c) for m in masks))
    assert len(best) == len(brute)
    inst = spark.createDataFrame([(i, f"s{j:02d}") for i in range(40) for j in np.flatnonzero(flags[i]).tolist()], "elem int, name string")
    found = setcover.greedy(inst)
    assert sum(c for _, c in found) == 40 and len(found) <= (math.log(40) + 1) * len(best)
    assert len(setcover.greedy_masks(masks)) == len(found)
    assert setcover.exact_cover([0, 1], 2) is None


def test_sketch_keeps_its_guarantee(spark, lineitem, tmp_path):
    ids, attrs = catalog.identity("lineitem"), catalog.attributes("lineitem")
    sets = [(",".join(c), list(c)) for k in (1, 2) for c in combinations(attrs, k)]
    truth = exact.unseparated_many(lineitem, sets).cache()
    for seed in (1, 2):
        sketch = nonsep.PairSketch.build(lineitem, 2, 0.01, 0.2, seed, ids, attrs, big_k=4)
        assert nonsep.zones(sketch.estimate_many(sets), truth, 0.01, 0.2).where("not holds and zone <> 'between'").isEmpty()
    sketch.save(str(tmp_path / "sketch"))
    again = nonsep.PairSketch.load(spark, str(tmp_path / "sketch"))
    assert again.estimate(["l_quantity"]) == sketch.estimate(["l_quantity"])
    with pytest.raises(ValueError):
        sketch.hits([("x", attrs[:3])])


def test_hard_inputs(spark):
    grid = hardness.grid(spark, 9, 4)
    assert grid.count() == 9**4 and hardness.grid_values(0.1) == 9
    assert exact.verdict(grid, ["x2"], 0.1).first().verdict == "bad"
    assert exact.verdict(hardness.grid(spark, 10, 4), ["x2"], 0.1).first().verdict == "slack"
    planted = hardness.planted(spark, 6_000, 0.001)
    assert exact.verdict(planted, ["x1"], 0.001).first().verdict == "bad" and exact.is_key(planted, ["x2"])
    got = {r.r: r.missed for r in hardness.planted_trials(spark, 6_000, bounds.planted_size(6_000, 0.001), [50, 200], 300, 1).collect()}
    for r, missed in got.items():
        p = bounds.planted_miss(6_000, bounds.planted_size(6_000, 0.001), r, True)
        assert abs(missed - p) < 5 * math.sqrt(p * (1 - p) / 300) + 1e-9
    got = {r.r: r.detected for r in hardness.grid_trials(spark, 99, 10, [12, 48], 200, 1).collect()}
    for r, detected in got.items():
        p = bounds.grid_detection(99, 10, r)["exact"]
        assert abs(detected - p) < 5 * math.sqrt(p * (1 - p) / 200) + 1e-9


def test_reconstruction_with_exact_counts(spark):
    k, t, m = 2, 3, 2
    matrix = hardness.weighted_matrix(spark, k, t, m, 5).cache()
    rows = matrix.collect()
    ones = {c: {r.row for r in rows if r[f"c{c}"]} for c in range(1, m + 1)}
    assert all(len(x) == k for x in ones.values())
    whole = hardness.block_table(matrix, k * t, m).cache()
    found = hardness.reconstruct(hardness.exact_estimates(whole), k, t, m, bounds.decoder_eps(t) * 0.99)
    assert hardness.hamming(ones, found)["cells"] == 0


def test_relational_helpers(spark):
    left = spark.createDataFrame([(1, "a", 10.0), (2, "a", 5.0), (3, "b", 7.0)], "i long, g string, at double")
    right = spark.createDataFrame([("a", 6.0, "x"), ("a", 10.0, "y"), ("b", 8.0, "z")], "g string, at double, v string")
    assert {r.i: r.as_of_v for r in relational.as_of(left, right, ["g"], "at", "v").collect()} == {1: "y", 2: None, 3: None}
    near = {(r.i, r.v_r) for r in relational.within(left, right, ["g"], "at", 1.0).collect()}
    assert near == {(1, "y"), (2, "x"), (3, "z")}
    nulls = spark.createDataFrame([(1, None), (2, None), (3, "k")], "i long, p string")
    assert {r.i for r in relational.rows_in_groups(nulls, ["p"]).collect()} == {1, 2}
    assert {r.i for r in relational.rows_in_groups(nulls, ["p"], alone=True).collect()} == {3}


def test_methods_from_sql(spark, lineitem):
    from sepkey.functions import sql_surface

    sql_surface.register(spark)
    lineitem.createOrReplaceTempView("lines")
    groups = spark.sql("SELECT count(*) AS k FROM lines GROUP BY l_linenumber")
    groups.createOrReplaceTempView("groups")
    p = spark.sql("SELECT noncollision(k, 2) AS p FROM groups").first().p
    assert p == pytest.approx(exact.unseparated(lineitem, ["l_linenumber"]).first().ratio)
    row = spark.sql("SELECT sum(pairs_of(k)) AS g, separation_verdict(sum(pairs_of(k)), sum(k), 0.001) AS v FROM groups").first()
    assert int(row.g) == gamma(lineitem, ["l_linenumber"]) and row.v == "bad"
    attrs = ["l_suppkey", "l_quantity", "l_linenumber", "l_discount"]
    sql_surface.sample_view(lineitem, "lines", 348, 42, catalog.identity("lineitem"), attrs)
    steps = spark.sql("SELECT * FROM greedy_trace(TABLE(sample_lines) WITH SINGLE PARTITION) ORDER BY step").collect()
    want = mincover.refine_greedy(filters.codes_of(spark.table("sample_lines").select(*attrs).toArrow()), attrs).steps
    assert [(r.attr, r.gamma_after) for r in steps] == want


NAN = float("nan")
HARD_VALUES = {
    "bigint": [2**53, 2**53 + 1, None],
    "double": [NAN, None, 1.0],
    "float": [0.1, None, NAN],
    "int": [1, None, 2],
    "string": ["", "NaN", None],
    "decimal(38,0)": [decimal.Decimal(2**80), decimal.Decimal(2**80 + 1), None],
    "array<double>": [[NAN], [None], [1.0], [], None],
    "array<array<int>>": [[[1], [2]], [[1, 2]], [[]], [None], []],
    "array<bigint>": [[2**53], [2**53 + 1], None],
    "struct<a: double, b: string>": [(None, "a"), (None, None), None, (NAN, "a")],
    "map<string,bigint>": [{"a": 1, "b": 2}, {"a": 1}, {"a": None}, {}],
    "binary": [b"a", b"b", None],
    "timestamp": [datetime.datetime(2020, 1, 1), None, datetime.datetime(2020, 1, 2)],
    "date": [datetime.date(2020, 1, 1), None, datetime.date(2020, 1, 2)],
    "boolean": [True, False, None],
}
#: Pairs of values that group together.
EQUAL_VALUES = {"double": [0.0, -0.0], "float": [NAN, NAN], "array<double>": [[0.0, NAN], [-0.0, NAN]], "struct<a: double, b: string>": [(0.0, None), (-0.0, None)], "map<string,double>": [{"a": 0.0, "b": NAN}, {"b": NAN, "a": -0.0}], "string": [None, None]}


@pytest.mark.parametrize("kind", [*HARD_VALUES, *(f"{k} equal" for k in EQUAL_VALUES)])
def test_answers_agree_on_every_type_with_nulls(spark, kind):
    """Driver-side codes, both answers inside Spark, and the exact verdict of all rows."""
    equal = kind.endswith(" equal")
    kind = kind.removesuffix(" equal")
    values = EQUAL_VALUES[kind] if equal else HARD_VALUES[kind]
    df = spark.createDataFrame(list(enumerate(values)), f"id long, x {kind}")
    kept = filters.TupleFilter.build(df, 0.1, 1, [F.col("id")], ["x"], r=10)
    sets = [("x", ["x"])]
    answers = [kept.accepts(["x"]), exact.is_key(df, ["x"]), kept.query_df(sets).first().accept, int(exact.unseparated_many(df, sets).first().gamma) == 0]
    if not kind.startswith("map"):
        answers.append(kept.query_df(sets, "sort").first().accept)
    assert set(answers) == {not equal}


def test_greedy_by_refinement_equals_counting_anew(spark):
    rng = random.Random(6)
    rows = [(rng.choice([None, 1, 2]), rng.choice([0.0, -0.0, NAN, None, 1.5]), rng.choice("abc"), rng.randrange(6)) for _ in range(400)]
    df = spark.createDataFrame(rows + rows[:3], "a int, b double, c string, d int")
    key = mincover.greedy_full(df, ["a", "b", "c", "d"])
    chosen, rest, gamma = [], ["a", "b", "c", "d"], None
    for attr, after in key.steps:
        scores = {a: int(exact.unseparated(df, [*chosen, a]).first().gamma) for a in rest}
        assert attr == min(rest, key=lambda a: scores[a]) and after == scores[attr]
        chosen.append(attr)
        rest.remove(attr)
        gamma = after
    assert key.residual == gamma > 0


def test_scratch_files_go_with_their_scope(spark):
    rows = spark.range(5)
    with stores.scratch():
        stays = stores.durable(rows, "stays", keep=True)
        with stores.scratch():
            inner = stores.durable(rows, "inner", keep=True)
            gone = stores.durable(rows, "gone")
        assert inner.count() == 5
        with pytest.raises(Exception):  # noqa: B017  Spark's own, by the reader's version
            gone.count()
    assert stays.count() == 5


def test_strategies_agree(spark):
    rng = random.Random(2)
    df = spark.createDataFrame([(rng.choice([None, 1, 2]), rng.choice([0.0, -0.0, NAN, None]), rng.choice("ab")) for _ in range(60)], "a int, b double, c string")
    sets = [(",".join(s), list(s)) for k in (1, 2, 3) for s in combinations("abc", k)]
    found = [sorted(map(tuple, exact.unseparated_many(df, sets, s).collect())) for s in ("per_set", "fingerprint", "grouping_sets", "lattice")]
    assert all(f == found[0] for f in found) and len(found[0]) == 7
    assert all(exact.unseparated_many(df.where("false"), sets, s).isEmpty() for s in ("per_set", "fingerprint"))


def test_attributes_may_have_any_name(spark):
    df = spark.createDataFrame([(1, 1, 1), (1, 1, 2), (2, 1, 2)], "k int, n int, gamma int")
    got = {r.set_name: int(r.gamma) for r in exact.unseparated_many(stores.durable(df), [("k", ["k"]), ("n", ["n"]), ("k,gamma", ["k", "gamma"])]).collect()}
    assert got == {"k": 1, "n": 3, "k,gamma": 0}


def test_sampling_without_replacement_doubles_the_ceiling_at_most(spark):
    for q, m, r in ((9, 4, 6), (99, 6, 9)):
        with_, without = bounds.grid_detection(q, m, r), bounds.grid_detection(q, m, r, False)
        assert without["rows_apart"] >= 0.5
        assert with_["exact"] <= without["exact"] <= 2 * with_["exact"] and without["ceiling"] <= 2 * with_["ceiling"]


def test_too_many_pairs_are_refused(spark, monkeypatch):
    monkeypatch.setattr(exact, "LISTED_PAIRS", 3)
    df = spark.range(4).select("id", F.lit(1).alias("x"))
    with pytest.raises(ValueError):
        exact.unseparated_edges(df, ["x"], "id")
    with pytest.raises(ValueError):
        mincover.instance(df, "id", ["x"])
