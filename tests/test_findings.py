"""Findings of the second round: whole jobs at size, and equality with the SQL on odd inputs."""

from __future__ import annotations

import math
import random
from itertools import combinations

import duckdb
from pyspark.sql import functions as F

import __spark_entry__ as entry
from sepkey.functions import bounds
from sepkey.operators import dealt, exact, filters, hardness, mincover, nonsep
from sepkey.plans import catalog, measures
from sepkey.sources.stores import table

SMALL = "/root/testdata/sf0.001"


def sql_rows(query: str, d: str, *names: str) -> list[tuple]:
    con = duckdb.connect()
    for name in names:
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM '{d}/{name}.parquet'")
    return sorted(con.sql(entry.oracle_sql()[query]).fetchall())


def rows_of(query: str, spark, d: str) -> list[tuple]:
    return sorted(tuple(r) for r in entry.queries()[query](spark, d).collect())


def test_f1_open_paths_without_listing_pairs(spark, monkeypatch):
    monkeypatch.setattr(exact, "LISTED_PAIRS", 3)
    monkeypatch.setattr(exact, "TASK_PAIRS", 5)
    assert rows_of("x7_transitivity_customer", spark, SMALL) == [(0,)]
    edges = {(1, 2), (2, 3), (1, 3), (4, 5), (5, 6), (6, 7), (8, 9), (9, 10)}
    whole = edges | {(b, a) for a, b in edges}
    want = sorted({(a, c) for a, b in whole for x, c in whole if b == x and a < c and (a, c) not in edges})
    df = spark.createDataFrame(sorted(edges), "a long, b long")
    assert sorted(map(tuple, exact.open_paths(df).collect())) == want
    assert sorted(map(tuple, exact.open_paths(df.unionByName(df.where("b = 5"))).collect())) == want


def test_f3_no_key_among_few_attributes(spark):
    df = spark.createDataFrame([(1, 1), (1, 1), (2, 1)], "p int, q int")
    assert mincover.minimum_key(df, ["p", "q"], 4) is None


def test_f10_greedy_pairs_of_any_number(spark, monkeypatch):
    monkeypatch.setattr(exact, "LISTED_PAIRS", 3)
    monkeypatch.setattr(exact, "TASK_PAIRS", 5)
    assert rows_of("k2_greedy_pairs_supplier", spark, SMALL) == sql_rows("k2_greedy_pairs_supplier", SMALL, "supplier")


def test_f11_classes_for_any_number_of_pairs(spark, monkeypatch):
    monkeypatch.setattr(exact, "LISTED_PAIRS", 3)
    assert rows_of("x6_edges_customer", spark, SMALL) == sql_rows("x6_edges_customer", SMALL, "customer")
    df = spark.createDataFrame([(1, None, 0.0), (2, None, -0.0), (3, "a", float("nan")), (4, "a", float("nan")), (5, "a", 1.0)], "id long, x string, y double")
    assert sorted(map(tuple, exact.unseparated_classes(df, ["x", "y"], "id").collect())) == [(1, 1, 1), (2, 1, 1), (3, 3, 1), (4, 3, 1), (5, 5, 0)]


def test_f12_days_round_as_their_sql(spark, tmp_path):
    con = duckdb.connect()
    times = ("00:00:00", "23:59:59.4", "23:59:59.499999", "23:59:59.5", "23:59:59.7", "11:00:00.5")
    values = ", ".join(f"({i}, TIMESTAMP '2024-01-01 {t}', 1, 'view')" for i, t in enumerate(times))
    con.sql(f"COPY (SELECT * FROM (VALUES {values}) v(event_id, ts, user_id, event_type)) TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    for query in ("st_window_gamma_events", "st_sliding_gamma_events"):
        assert rows_of(query, spark, str(tmp_path)) == sql_rows(query, str(tmp_path), "events")


def test_f13_planted_cluster_with_repeated_identities(spark):
    rows = table(spark, SMALL, "lineitem").limit(50).select("l_orderkey", "l_tax", F.explode(F.array(*map(F.lit, range(7)))).alias("copy"))
    n = rows.count()
    c = hardness.bounds.planted_size(n, 0.001)
    got = exact.unseparated(hardness.planted_on(rows, [F.col("l_orderkey")], n, 0.001, 42), ["planted"]).first()
    assert (got.n, int(got.gamma), got.max_group) == (n, c * (c - 1) // 2, c)


def test_f2_to_f9_sets_are_counted_inside_dealt_parts(spark, monkeypatch):
    rng = random.Random(5)
    rows = [(rng.randrange(900), rng.choice([None, 0.0, -0.0, float("nan"), 1.5]), rng.choice(["a", "b", None]), i % 700, rng.randrange(2), 2**62 + i % 500) for i in range(1500)]
    df = spark.createDataFrame(rows, "a int, b double, c string, d long, e int, f long")
    sets = [(",".join(s), list(s)) for k in range(7) for s in combinations("abcdef", k)]
    want = sorted(map(tuple, exact.unseparated_many(df, sets, "lattice").collect()))
    for part, most in ((100, 400), (100, 120), (10, 5), (10_000, 10_000)):  # even, some uneven, none, all in few parts
        monkeypatch.setattr(dealt, "PART_ROWS", part)
        monkeypatch.setattr(dealt, "MOST_ROWS", most)
        assert sorted(map(tuple, exact.unseparated_many(df, sets, "dealt").collect())) == want
    assert exact.unseparated_many(df.where("false"), sets, "dealt").isEmpty()
    taken = []
    monkeypatch.setattr(exact, "DEALT_CELLS", 10)
    monkeypatch.setattr(exact, "_dealt", lambda df, sets: taken.append(len(sets)) or df)
    exact.unseparated_many(df, sets)
    assert taken == [64]


def test_f8_f9_smaller_samples_are_parts_of_larger_ones(spark):
    rows, ids, attrs = table(spark, SMALL, "lineitem"), catalog.identity("lineitem"), catalog.attributes("lineitem")[:4]
    sets = catalog.named(catalog.random_sets(attrs, 10))
    truth = {x.set_name: (int(x.gamma), x.n) for x in exact.unseparated_many(rows, sets).collect()}
    got = {(r.inverse_eps, r.factor_percent): (r.bad_sets, r.accepted_bad) for r in measures.sensitivity(spark, rows, sets, ids, attrs, 42).collect()}
    for eps, c in ((0.1, 0.25), (0.001, 1.0)):
        kept = filters.TupleFilter.build(rows, eps, 42, ids, attrs, c=c).query_many(sets)
        bad = {s for s, (gamma, n) in truth.items() if gamma > eps * bounds.pairs_of(n)}
        assert got[round(1 / eps), round(100 * c)] == (len(bad), sum(kept[s] for s in bad))
    part = nonsep.PairSketch.build(rows, 2, 0.1, 0.2, 42, ids, attrs).first(1, 0.1, 0.2)
    alone = nonsep.PairSketch.build(rows, 1, 0.1, 0.2, 42, ids, attrs)
    assert part.about == alone.about and sorted(map(tuple, part.flags.collect())) == sorted(map(tuple, alone.flags.collect()))


def test_f18_replacement_ratio_of_the_given_tables(spark):
    got = rows_of("a3_replacement_ratio", spark, SMALL)
    assert got == sql_rows("a3_replacement_ratio", SMALL, "orders", "lineitem", "events")
    assert sorted(r[0] for r in got) == sorted(table(spark, SMALL, t).count() for t in ("orders", "lineitem", "events"))


def test_f14_planted_miss_on_the_given_tables(spark):
    got = rows_of("a10_planted_miss", spark, SMALL)
    assert got == sql_rows("a10_planted_miss", SMALL, "orders", "lineitem")
    assert {r[0] for r in got} == {table(spark, SMALL, t).count() for t in ("orders", "lineitem")}


def test_f25_grid_trials_drawn_from_customer(spark, tmp_path):
    got = rows_of("h2_grid_trials", spark, SMALL)
    assert got == sql_rows("h2_grid_trials", SMALL, "customer") and [r[0] for r in got] == [6, 12, 24, 48, 96]
    rows = table(spark, SMALL, "customer")
    trials = {r.r: r.trials for r in hardness.grid_trials_on(rows, "c_custkey", 99, 20, [6, 96], 42).collect()}
    assert trials == {6: 2, 96: 1}  # 150 rows: the second trial is short
    rows.limit(50).unionByName(rows.limit(20)).selectExpr("nullif(c_custkey, 7) AS c_custkey").write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
    assert rows_of("h2_grid_trials", spark, str(tmp_path)) == sorted(con.sql(entry.oracle_sql()["h2_grid_trials"]).fetchall())


def test_f24_grid_of_the_values_in_lineitem(spark):
    got = rows_of("h1_grid_singletons", spark, SMALL)
    assert got == sql_rows("h1_grid_singletons", SMALL, "lineitem")
    rows = table(spark, SMALL, "lineitem")
    q = {r[0]: rows.select(r[0]).distinct().count() for r in got}
    size = q["l_linenumber"] * q["l_discount"] * q["l_tax"] * q["l_returnflag"]
    assert {r[0]: r[1] for r in got} == {a: x * bounds.pairs_of(size // x) for a, x in q.items()}
    odd = spark.createDataFrame([(1, None), (1, None), (2, "a"), (None, "a")], "x int, y string")
    assert hardness.grid_on(odd, ["x", "y"]).count() == 6


def test_f15_block_gamma_counted_on_orders(spark):
    got = rows_of("a12_block_gamma", spark, SMALL)
    assert got == sql_rows("a12_block_gamma", SMALL, "orders")
    n = table(spark, SMALL, "orders").count()
    assert {r[0] * r[1] for r in got} == {n} and all(g == bounds.block_gamma(t, k, u) for t, k, u, g in got)  # n is a multiple of 2 to 5
    few = table(spark, SMALL, "orders").limit(7)
    assert hardness.block_counts(few, "o_orderkey", [(3, 3, 0), (3, 3, 2), (0, 0, 0)]) == [45 + 0, 28 + 3, 21 + 21]


def test_f16_threshold_against_guesses_counted_on_events(spark):
    got = rows_of("a13_threshold", spark, SMALL)
    assert got == sql_rows("a13_threshold", SMALL, "events")
    assert [r[1] for r in got] == [1000 // t for t in range(2, 7)]
    for t, k, threshold, _, right, wrong in got:
        counted = lambda u, k=k: bounds.pairs_of(1000 + k - u) + bounds.pairs_of(1000 - 2 * k + u)
        assert right == (counted(k) <= threshold) and wrong == (counted(9 * k // 10) > threshold)
    assert [r[5] for r in got][:3] == [True, True, False]  # an estimate within 1 % tells them apart only where the decoder needs no less


def test_f20_pair_miss_of_the_sets_of_orders(spark, tmp_path):
    got = rows_of("a6_pair_miss", spark, SMALL)
    assert got == sql_rows("a6_pair_miss", SMALL, "orders")
    truth = {r.set_name: (int(r.gamma), r.n) for r in exact.unseparated_many(table(spark, SMALL, "orders"), catalog.named(catalog.SETS["orders"])).collect()}
    for name, pairs, micro in got:
        gamma, n = truth[name]
        assert pairs == 60_000 and abs(micro / 1e6 - pairs * math.log(1 - gamma / bounds.pairs_of(n))) < 1e-4
    con = duckdb.connect()
    con.sql(f"COPY (SELECT o_orderkey, 1 AS o_custkey, NULL::VARCHAR AS o_orderstatus, o_totalprice, o_orderdate, o_orderpriority FROM '{SMALL}/orders.parquet' LIMIT 9) TO '{tmp_path}/orders.parquet' (FORMAT parquet)")
    got = dict((r[0], r[2]) for r in entry.queries()["a6_pair_miss"](spark, str(tmp_path)).collect())
    assert got == dict((r[0], r[2]) for r in sql_rows("a6_pair_miss", str(tmp_path), "orders")) and got["o_custkey"] is None and got["o_orderstatus"] is None


def test_f21_grid_ceiling_for_the_values_of_lineitem(spark):
    got = rows_of("a9_grid_ceiling", spark, SMALL)
    assert got == sql_rows("a9_grid_ceiling", SMALL, "lineitem") and len(got) == 18
    rows = table(spark, SMALL, "lineitem")
    assert {r[:2] for r in got} == {(a, rows.select(a).distinct().count()) for a in ("l_linenumber", "l_discount", "l_quantity")}


def test_f22_grid_without_replacement_for_the_values_of_lineitem(spark, tmp_path):
    got = rows_of("a9_grid_without_replacement", spark, SMALL)
    assert got == sql_rows("a9_grid_without_replacement", SMALL, "lineitem") and len(got) == 18
    con = duckdb.connect()
    con.sql(f"COPY (SELECT 1 AS l_linenumber, NULL::DOUBLE AS l_discount, (i % 2)::DOUBLE AS l_quantity FROM range(9) r(i)) TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    for query in ("a9_grid_ceiling", "a9_grid_without_replacement"):  # fewer values than draws
        assert rows_of(query, spark, str(tmp_path)) == sql_rows(query, str(tmp_path), "lineitem")


def test_f17_tails_for_the_shares_of_events(spark):
    got = rows_of("a15_sketch_tails", spark, SMALL)
    assert got == sql_rows("a15_sketch_tails", SMALL, "events")
    truth = exact.unseparated(table(spark, SMALL, "events"), ["event_type"]).first()
    want = bounds.sketch_tail(50_000, 1 - truth.ratio, 0.1)
    assert abs(next(r[3] for r in got if r[:3] == ("event_type", 50_000, 10)) / 1e6 - want) < 1e-6


def test_f19_profiles_of_the_bad_sets_of_lineitem(spark):
    got = rows_of("a4_wide_profiles", spark, SMALL)
    truth = exact.unseparated_many(table(spark, SMALL, "lineitem"), catalog.named(catalog.SETS["lineitem"][:6])).collect()
    bad = {x.set_name: x.groups for x in truth if x.gamma > 0.001 * bounds.pairs_of(x.n)}
    assert bad and {r[0] for r in got} == set(bad) and all(r[6] for r in got)
    assert all((r[2] is None) == (bad[r[0]] < r[1]) for r in got)  # fewer groups than tuples: two must meet
    hist = [c for c in table(spark, SMALL, "lineitem").groupBy("l_quantity").count().select("count").toPandas()["count"]]
    ways = [1.0] + [0.0] * 50  # elementary symmetric sums, one group after another
    for c in hist:
        for i in range(50, 0, -1):
            ways[i] += ways[i - 1] * c / sum(hist)
    real = next(r[2] for r in got if r[:2] == ("l_quantity", 50))
    assert len(hist) == 50 and abs(real / 1e6 - math.lgamma(51) - math.log(ways[50])) < 1e-5


def test_f23_bounds_of_the_given_tables(spark):
    got = {r[:3]: r[3] for r in rows_of("a_bounds_table", spark, SMALL)}
    assert {k[0] for k in got} == {"customer", "orders", "lineitem", "events"} and len(got) == 4 * 18
    rows = table(spark, SMALL, "lineitem")
    n, r = rows.count(), bounds.tuple_sample_size(11, 0.001)
    top = max(rows.groupBy(c).count().agg(F.max("count")).first()[0] for c in rows.columns)
    assert got["lineitem", "heaviest_group", n] == round(top / n * 1e6)
    assert got["lineitem", "heaviest_group_missed", r] == round(1e6 * bounds.log_two_valued(r, top / n, 1, 1 - top / n))
    assert got["lineitem", "exact", r] == 0 and got["customer", "exact", bounds.tuple_sample_size(5, 0.001)] == 1_000_000  # 150 customers: the sample holds all
    empty = measures.bounds_table({"x": rows.where("false")})
    assert empty.where("name = 'heaviest_group'").first().value_micro == 0
