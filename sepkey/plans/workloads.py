"""More registered queries: both filters on every workload, measures, bounds, streams and built-in comparisons, each beside its SQL."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sepkey.functions import bounds
from sepkey.operators import exact, filters, mincover, nonsep, sampling
from sepkey.plans import catalog, measures, sqltext
from sepkey.plans.queries import _APART, _NO_ID, _R, _S, _SK, _SK_SETS, _SQL_VALUES, _values, EPS, QUERIES, SEED, _is_folder, _micro, _shared, _sketch, _sql_shared, _trace, add, frame
from sepkey.sources.stores import table
from sepkey.streaming import samplers

# -- both filters on every workload

#: Workload: (attributes, eps, sets).
WORKLOADS = {
    "events": (catalog.attributes("events"), EPS, catalog.random_sets(catalog.attributes("events"), 60)),
    "part": (_NO_ID["part"], EPS, catalog.random_sets(_NO_ID["part"], 31)),
    "customer": (_NO_ID["customer"], 0.01, catalog.random_sets(_NO_ID["customer"], 7)),
    "supplier": (["s_nationkey", "s_name", "s_acctbal"], 0.1, catalog.random_sets(["s_nationkey", "s_name", "s_acctbal"], 7)),
    "signs": (catalog.attributes("signs"), 0.1, catalog.random_sets(catalog.attributes("signs"), 100, largest=12)),
    "flags": (catalog.attributes("flags"), 0.05, catalog.random_sets(catalog.attributes("flags"), 100)),
    "conversations": (catalog.attributes("conversations"), 0.01, catalog.random_sets(catalog.attributes("conversations"), 15)),
    "nullable": (catalog.attributes("nullable"), EPS, catalog.random_sets(catalog.attributes("nullable"), 63)),
}


def _both(spark, d, name) -> DataFrame:
    """set_name, tuple_accept, pair_accept."""
    attrs, eps, sets = WORKLOADS[name]
    rows, ids, sets = catalog.source(spark, d, name), catalog.identity(name), catalog.named(sets)
    a = filters.TupleFilter.build(rows, eps, SEED, ids, attrs).query_many(sets)
    b = filters.PairFilter.build(rows, eps, SEED, ids, attrs).query_many(sets)
    return frame(spark, "set_name string, tuple_accept boolean, pair_accept boolean", [(n, a[n], b[n]) for n, _ in sets])


def _judged(spark, d, name) -> DataFrame:
    _, eps, sets = WORKLOADS[name]
    truth = exact.unseparated_many(catalog.source(spark, d, name), catalog.named(sets))
    return measures.confusion(_both(spark, d, name), truth.select("set_name", exact.verdict_of(F.col("gamma"), F.col("n"), eps).alias("verdict")))


_AGREE = (
    "SELECT CAST(count(*) AS BIGINT) AS sets, CAST(count(*) FILTER (WHERE tuple_accept = pair_accept) AS BIGINT) AS agree,"
    " CAST(count(*) FILTER (WHERE pair_accept AND NOT tuple_accept) AS BIGINT) AS only_pairs_accept FROM ({})"
)
_BROKEN = (
    "SELECT CAST(count(*) FILTER (WHERE verdict = 'key' AND NOT tuple_accept) AS BIGINT) AS tuple_rejects_key,"
    " CAST(count(*) FILTER (WHERE verdict = 'bad' AND tuple_accept) AS BIGINT) AS tuple_accepts_bad,"
    " CAST(count(*) FILTER (WHERE verdict = 'key' AND NOT pair_accept) AS BIGINT) AS pair_rejects_key,"
    " CAST(count(*) FILTER (WHERE verdict = 'bad' AND pair_accept) AS BIGINT) AS pair_accepts_bad FROM ({}) JOIN ({}) USING (set_name)"
)

for _n, (_attrs, _eps, _sets) in WORKLOADS.items():
    _named = catalog.named(_sets)
    _sql = sqltext.both_filters(_n, _attrs, _named, bounds.tuple_sample_size(len(_attrs), _eps), bounds.pair_sample_size(len(_attrs), _eps))
    _true = sqltext.verdicts(f"({catalog.source_sql(_n)})", _named, _eps)
    add(f"m3_agreement_{_n}", lambda spark, d, n=_n: measures.agreement(_both(spark, d, n)), _AGREE.format(_sql))
    add(f"m6_confusion_{_n}", lambda spark, d, n=_n: _judged(spark, d, n), f"SELECT verdict, tuple_accept, pair_accept, CAST(count(*) AS BIGINT) AS sets FROM ({_sql}) JOIN ({_true}) USING (set_name) GROUP BY ALL")
    add(f"f9_contract_{_n}", lambda spark, d, n=_n: measures.violations(_judged(spark, d, n)), _BROKEN.format(_sql, _true))


def _ways(spark, d) -> DataFrame:
    """On a table with nulls, NaN and wide integers: answers by driver-side codes, by hashes, by sorting, and whether the set is a key."""
    attrs, eps, sets = WORKLOADS["nullable"]
    rows, sets = catalog.nullable(spark, d), catalog.named(sets)[:20]
    kept = filters.TupleFilter.build(rows, eps, SEED, catalog.identity("nullable"), attrs)
    codes = frame(spark, "set_name string, by_codes boolean", [(n, kept.accepts(a)) for n, a in sets])
    hashes = kept.query_df(sets).withColumnRenamed("accept", "by_hashes")
    ordered = kept.query_df(sets, "sort").withColumnRenamed("accept", "by_order")
    truth = exact.unseparated_many(rows, sets).select("set_name", (F.col("gamma") == 0).alias("is_key"))
    return codes.join(hashes, "set_name").join(ordered, "set_name").join(truth, "set_name")


def _ways_sql() -> str:
    attrs, eps, sets = WORKLOADS["nullable"]
    sets = catalog.named(sets)[:20]
    accepts = sqltext.tuple_accepts("nullable", sets, bounds.tuple_sample_size(len(attrs), eps))
    truth = sqltext.gamma(f"({catalog.NULLABLE_SQL})", sets)
    return f"SELECT set_name, accept AS by_codes, accept AS by_hashes, accept AS by_order, gamma = 0 AS is_key FROM ({accepts}) JOIN ({truth}) USING (set_name)"


add("f9_ways_with_nulls", _ways, _ways_sql())

# -- small keys


def _forced(spark, d):
    allowed = [a for a in catalog.attributes("lineitem") if a != "l_extendedprice"]
    key = mincover.find_key(table(spark, d, "lineitem"), EPS, SEED, catalog.identity("lineitem"), catalog.attributes("lineitem"), must_include=["l_returnflag"], exclude=["l_extendedprice"])
    assert set(key.attrs) <= set(allowed)
    return _trace(spark, key)


_ALLOWED = [a for a in catalog.attributes("lineitem") if a != "l_extendedprice"]
add("k13_forced_attribute_lineitem", _forced, sqltext.greedy_trace(sqltext.tuple_sample("lineitem", _R["lineitem"]), _ALLOWED, first=("l_returnflag",)))

_VERDICT = f"CASE WHEN gamma = 0 THEN 'key' WHEN CAST(gamma AS DOUBLE) <= {EPS} * CAST(n * (n - 1) // 2 AS DOUBLE) THEN 'slack' ELSE 'bad' END"
_FOUND = sqltext.found_gamma("lineitem", sqltext.tuple_sample("lineitem", _R["lineitem"]), catalog.attributes("lineitem"))
add("k12_validate_lineitem", QUERIES["k12_validate_lineitem"], f"SELECT attrs, gamma, {_VERDICT} AS verdict FROM ({_FOUND})")


def _size_ratio_sql(t: str) -> str:
    attrs = _NO_ID[t]
    r, s = bounds.tuple_sample_size(len(attrs), EPS), bounds.pair_sample_size(len(attrs), EPS)
    found = sqltext.found_gamma(t, sqltext.tuple_sample(t, r), attrs)
    steps = lambda sql: f"SELECT CAST(count(*) AS BIGINT) FROM ({sql})"
    least = sqltext.first_smallest([(z, i, ",".join(c), f"NOT EXISTS (SELECT 1 FROM {t} GROUP BY {', '.join(c)} HAVING count(*) > 1)") for z, i, c in sqltext.subsets(attrs, len(attrs))])
    pairs = sqltext.pair_trace(sqltext.pair_flags(t, attrs, s), attrs)
    return (
        f"SELECT '{t}' AS name, size AS tuple_greedy, ({steps(pairs)}) AS pair_greedy, ({steps(sqltext.greedy_trace(t, attrs))}) AS full_greedy,"
        f" coalesce((SELECT size FROM ({least})), 0) AS minimum, CAST(floor(CAST(gamma AS DOUBLE) / CAST(n * (n - 1) // 2 AS DOUBLE) * 1e9) AS BIGINT) AS together_ppb FROM ({found})"
    )


add("m5_size_ratio", QUERIES["m5_size_ratio"], " UNION ALL ".join(f"SELECT * FROM ({_size_ratio_sql(t)})" for t in ("part", "customer", "orders")))


def _least_key(t):
    def run(spark, d):
        found = mincover.minimum_key(table(spark, d, t), _NO_ID[t], 4)
        return frame(spark, "attrs string, size long", [(",".join(found), len(found))] if found else [])

    return run


for _t in ("customer", "orders"):
    _tests = [(z, i, ",".join(c), f"NOT EXISTS (SELECT 1 FROM {_t} GROUP BY {', '.join(c)} HAVING count(*) > 1)") for z, i, c in sqltext.subsets(_NO_ID[_t], 4)]
    add(f"k8_minimum_key_{_t}", _least_key(_t), sqltext.first_smallest(_tests))

for _t in ("part", "customer"):
    _attrs = _NO_ID[_t]
    _rt, _st = bounds.tuple_sample_size(len(_attrs), EPS), bounds.pair_sample_size(len(_attrs), EPS)
    _all = sqltext.subsets(_attrs, len(_attrs))

    def _smallest(spark, d, t=_t, attrs=_attrs, method="tuple_exact"):
        key = mincover.find_key(table(spark, d, t), EPS, SEED, catalog.identity(t), attrs, method=method)
        return frame(spark, "size long", [(len(key.attrs),)])

    _by_tuples = [(z, i, ",".join(c), f"NOT EXISTS (SELECT 1 FROM s GROUP BY {', '.join(c)} HAVING count(*) > 1)") for z, i, c in _all]
    _by_pairs = [(z, i, ",".join(c), f"(SELECT NOT coalesce(bool_or({' AND '.join(c)}), false) FROM p)") for z, i, c in _all]
    add(f"k6_tuple_exact_{_t}", _smallest, f"SELECT size FROM ({sqltext.first_smallest(_by_tuples, f'WITH s AS MATERIALIZED {sqltext.tuple_sample(_t, _rt)}')})")
    add(f"k7_pair_exact_{_t}", lambda spark, d, f=_smallest: f(spark, d, method="pair_exact"), f"SELECT size FROM ({sqltext.first_smallest(_by_pairs, f'WITH {sqltext.pair_flags(_t, _attrs, _st)}')})")

# -- measures

_LINE_SETS = catalog.named(catalog.random_sets(catalog.attributes("lineitem")))
_SEEDS = range(10)


def _failures_sql() -> str:
    attrs, truth = catalog.attributes("lineitem"), sqltext.verdicts("lineitem", _LINE_SETS, EPS)
    trials = " UNION ALL ".join(f"SELECT {seed} AS seed, * FROM ({sqltext.both_filters('lineitem', attrs, _LINE_SETS, _R['lineitem'], _S['lineitem'], seed)})" for seed in _SEEDS)
    wrong = "CAST(sum(CASE WHEN (verdict = 'key' AND NOT {0}) OR (verdict = 'bad' AND {0}) THEN 1 ELSE 0 END) AS BIGINT) AS {1}"
    per = f"SELECT seed, {wrong.format('tuple_accept', 'a')}, {wrong.format('pair_accept', 'b')} FROM ({trials}) JOIN ({truth}) USING (set_name) GROUP BY seed"
    one = "SELECT '{0}' AS method, CAST(count(*) AS BIGINT) AS trials, CAST(count(*) FILTER (WHERE {1} > 0) AS BIGINT) AS failed, CAST(sum({1}) AS BIGINT) AS wrong FROM t"
    return f"WITH t AS MATERIALIZED ({per}) {one.format('tuples', 'a')} UNION ALL {one.format('pairs', 'b')}"


add("m7_failure_trials_lineitem", QUERIES["m7_failure_trials_lineitem"], _failures_sql())


def _sensitivity_sql() -> str:
    m, out = len(catalog.attributes("lineitem")), []
    for eps in (0.1, 0.01, 0.001):
        for c in (0.25, 0.5, 1.0, 2.0, 4.0):
            r = bounds.tuple_sample_size(m, eps, c=c)
            accepts = sqltext.tuple_accepts("lineitem", _LINE_SETS, r)
            bad = f"CAST(gamma AS DOUBLE) > {eps} * CAST(n * (n - 1) // 2 AS DOUBLE)"
            out.append(
                f"SELECT CAST({round(1 / eps)} AS BIGINT) AS inverse_eps, CAST({round(100 * c)} AS BIGINT) AS factor_percent, CAST({r} AS BIGINT) AS tuples,"
                f" CAST(count(*) FILTER (WHERE {bad}) AS BIGINT) AS bad_sets, CAST(count(*) FILTER (WHERE {bad} AND accept) AS BIGINT) AS accepted_bad FROM ({accepts}) JOIN truth USING (set_name)"
            )
    return f"WITH truth AS MATERIALIZED ({sqltext.gamma('lineitem', _LINE_SETS)}) " + " UNION ALL ".join(out)


add("w11_sensitivity_lineitem", QUERIES["w11_sensitivity_lineitem"], _sensitivity_sql())


def _touched(spark, d):
    """How many rows the baseline's pairs read, beside the tuples of the method."""
    rows = table(spark, d, "orders")
    drawn = sampling.pair_draws(rows, _S["orders"], rows.count(), SEED)
    ends = drawn.select(F.explode(F.array("i", "j")).alias("ordinal"))
    return ends.agg(F.countDistinct("ordinal").alias("touched")).select(F.lit(_S["orders"]).cast("long").alias("pairs"), "touched", F.lit(_R["orders"]).cast("long").alias("tuples"))


_DRAWN = sqltext.pair_draws("orders", _S["orders"])
add(
    "m1_touched_rows_orders",
    _touched,
    f"WITH o AS (SELECT * FROM orders) SELECT CAST({_S['orders']} AS BIGINT) AS pairs, CAST(count(DISTINCT ordinal) AS BIGINT) AS touched, CAST({_R['orders']} AS BIGINT) AS tuples"
    f" FROM (SELECT unnest([i, j]) AS ordinal FROM {_DRAWN})",
)


def _errors(spark, d):
    truth = exact.unseparated_many(table(spark, d, "lineitem"), _SK_SETS)
    z = nonsep.zones(_sketch(spark, d).estimate_many(_SK_SETS), truth, _SK["alpha"], _SK["eps"])
    error = F.floor(F.abs(F.col("gamma_hat").cast("double") / F.col("gamma").cast("double") - 1) * 1e6).cast("long")
    return z.select("set_name", "status", F.coalesce(error, F.lit(-1)).alias("error_ppm"))


_S_LI = bounds.sketch_pairs(11, **_SK)
_LEAST = _SK["alpha"] * _S_LI / 10
_TOTAL = "(SELECT CAST(count(*) * (count(*) - 1) // 2 AS DOUBLE) FROM lineitem)"
add(
    "m9_error_lineitem",
    _errors,
    f"SELECT set_name, CASE WHEN hits < {_LEAST!r} THEN 'small' ELSE 'estimate' END AS status,"
    f" CASE WHEN hits < {_LEAST!r} THEN -1 ELSE CAST(floor(abs(round(CAST(hits AS DOUBLE) / {_S_LI} * {_TOTAL}) / CAST(gamma AS DOUBLE) - 1) * 1e6) AS BIGINT) END AS error_ppm"
    f" FROM ({sqltext.hits('lineitem', catalog.attributes('lineitem'), _SK_SETS, _S_LI)}) JOIN ({sqltext.gamma('lineitem', _SK_SETS)}) USING (set_name)",
)
add("m10_sketch_bits_lineitem", lambda spark, d: frame(spark, "stored_bits long, pairs long", [((k := _sketch(spark, d)).stored_bits(), k.about["s"])]), f"SELECT CAST({_S_LI * 11} AS BIGINT) AS stored_bits, CAST({_S_LI} AS BIGINT) AS pairs")


def _reduction(spark, d):
    """Sampled pairs over sampled tuples: the reduction of the sample, 1 / sqrt(eps)."""
    sizes = [(m, bounds.pair_sample_size(m, EPS), bounds.tuple_sample_size(m, EPS)) for m in (13, 55, 372)]
    return frame(spark, "m long, pairs long, tuples long, reduction_milli long", [(m, s, r, math.floor(1000 * s / r)) for m, s, r in sizes])


add(
    "m12_sample_reduction",
    _reduction,
    "SELECT CAST(m AS BIGINT) AS m, CAST(m * 1000 AS BIGINT) AS pairs, CAST(round(m * sqrt(1000.0)) AS BIGINT) AS tuples,"
    " CAST(floor(1000.0 * (m * 1000) / round(m * sqrt(1000.0))) AS BIGINT) AS reduction_milli FROM (VALUES (13), (55), (372)) v(m)",
)

# -- bounds


def _grid_without(spark, d):
    got = [(a, q, m, r, bounds.grid_detection(q, m, r, False)) for a, q in _values(spark, d) for m in (4, 6) for r in (3, 6, 9)]
    return frame(spark, "attribute string, q long, m long, r long, apart_ppm long, exact_ppm long, ceiling_ppm long", [(a, q, m, r, _micro(x["rows_apart"]), _micro(x["exact"]), _micro(x["ceiling"])) for a, q, m, r, x in got])


add(
    "a9_grid_without_replacement",
    _grid_without,
    "SELECT attribute, CAST(q AS BIGINT) AS q, CAST(m AS BIGINT) AS m, CAST(r AS BIGINT) AS r, CAST(floor(a * 1e6 + 0.5) AS BIGINT) AS apart_ppm,"
    " CASE WHEN a = 0 THEN 1000000 ELSE CAST(floor(least(1, pow(1 - c, m) / a) * 1e6 + 0.5) AS BIGINT) END AS exact_ppm,"
    " CASE WHEN a = 0 THEN 1000000 ELSE CAST(floor(least(1, pow(1 - 1.0::DOUBLE / m, m) / a) * 1e6 + 0.5) AS BIGINT) END AS ceiling_ppm"
    f" FROM (SELECT attribute, q, m, r, {_APART.format('q')} AS c, {_APART.format('pow(CAST(q AS DOUBLE), m)')} AS a FROM {_SQL_VALUES} x, (VALUES (4), (6)) y(m), (VALUES (3), (6), (9)) z(r))",
)


def _tails(spark, d):
    """How far a sketch's counts may be off, for the shares that sets of events have on all rows."""
    rows = [(n, s, e, bounds.sketch_tail(s, p, e)) for n, p in _shared(spark, d, "events") for s in (1000, 50_000) for e in (0.1, 0.2)]
    return frame(spark, "set_name string, pairs long, inverse_eps long, tail_ppm long", [(n, s, round(1 / e), _micro(x)) for n, s, e, x in rows])


add(
    "a15_sketch_tails",
    _tails,
    "SELECT set_name, CAST(s AS BIGINT) AS pairs, CAST(e AS BIGINT) AS inverse_eps,"
    " CAST(floor(least(1, 2 * exp(-(1.0::DOUBLE / e) * (1.0::DOUBLE / e) * s * p / 3)) * 1e6 + 0.5) AS BIGINT) AS tail_ppm"
    f" FROM {_sql_shared('events')}, (VALUES (1000), (50000)) a(s), (VALUES (10), (5)) c(e)",
)


#: Sets of lineitem that are bad, or may be: they have few groups.
_PROFILED = catalog.named(catalog.SETS["lineitem"][:6])


def _wide_family(spark, d):
    """The chance that r tuples miss each set that is bad among the first of lineitem's, from the sizes of all its groups, beside the worst profile of the
    planner's family and of a wider one with finitely many smaller groups: logs in millionths; null: it cannot be missed."""
    rows, sizes = table(spark, d, "lineitem"), None
    for name, attrs in _PROFILED:
        one = exact.clique_histogram(rows, attrs).select(F.lit(name).alias("set_name"), "size", "groups")
        sizes = one if sizes is None else sizes.unionByName(one)
    found: dict[str, list[tuple[int, int]]] = {}
    for x in sizes.collect():  # distinct sizes: at most sqrt(2 n) a set
        found.setdefault(x.set_name, []).append((x["size"], x["groups"]))
    out = []
    for r in (50, 158, 348):
        plain, wide = bounds.worst_profile(r, EPS), bounds.worst_profile(r, EPS, groups=bounds.WIDE_GROUPS, rest=bounds.WIDE_REST)
        for name, hist in sorted(found.items()):
            n, gamma = sum(a * k for a, k in hist), sum(bounds.pairs_of(a) * k for a, k in hist)
            if gamma > EPS * bounds.pairs_of(n):
                miss = bounds.log_noncollision(hist, r) if sum(k for _, k in hist) >= r else -math.inf
                covers = max(miss, wide["log_miss"]) <= plain["log_miss"] + 1e-9
                out.append((name, r, _micro(miss) if miss > -math.inf else None, _micro(plain["log_miss"]), _micro(wide["log_miss"]), wide["ka"], covers))
    return frame(spark, "set_name string, r long, real_micro long, planner_micro long, wide_micro long, wide_ka long, planner_covers boolean", out)


add("a4_wide_profiles", _wide_family)

_PLANTED = "CAST(ceil(sqrt(0.001::DOUBLE) * n) AS BIGINT) + 1"
_NONE = "exp((SELECT sum(ln(CAST(n - c - i.range AS DOUBLE) / (n - i.range))) FROM range(r) i))"
_ONE = "r * CAST(c AS DOUBLE) / (n - r + 1) * exp(coalesce((SELECT sum(ln(CAST(n - c - i.range AS DOUBLE) / (n - i.range))) FROM range(r - 1) i), 0))"
add(
    "a10_planted_miss",
    QUERIES["a10_planted_miss"],
    "SELECT CAST(n AS BIGINT) AS n, CAST(r AS BIGINT) AS r, CAST(floor(p * 1e6 + 0.5) AS BIGINT) AS exact_ppm, CAST(floor(p * 1e6 + 0.5) AS BIGINT) AS hypergeometric_ppm"
    f" FROM (SELECT n, r, {_NONE} + {_ONE} AS p FROM (SELECT n, r, {_PLANTED} AS c FROM (SELECT count(o_orderkey) AS n FROM orders UNION ALL SELECT count(l_orderkey) FROM lineitem) a, (VALUES (50), (100), (190), (348)) b(r)))",
)

# -- streams

_SLOTS = 12


def _slots(spark, d) -> samplers.PairSlotSampler:
    """events as a file stream into the sampler of pairs."""
    path = f"{d}/events.parquet"
    rows = table(spark, d, "events").select("event_id", "user_id", "event_type")
    stream = spark.readStream.schema(table(spark, d, "events").schema).parquet(path if _is_folder(spark, path) else f"{d}/events*.parquet")
    kept = samplers.PairSlotSampler(spark, _SLOTS, SEED, [F.col("event_id")])
    kept.start(stream.select(*rows.columns), f"{kept.path}-log").awaitTermination()
    return kept


_SLOT_HASH = f"md5(concat_ws('|', '{SEED}', CAST(slot AS VARCHAR), CAST(event_id AS VARCHAR)))"
_SLOT_SQL = (
    f"SELECT slot, max(event_id) FILTER (WHERE nth = 1) AS l, max(event_id) FILTER (WHERE nth = 2) AS r FROM (SELECT slot, event_id, row_number() OVER (PARTITION BY slot ORDER BY {_SLOT_HASH}) AS nth"
    f" FROM (SELECT range AS slot FROM range({_SLOTS})), events) WHERE nth <= 2 GROUP BY slot"
)
add(
    "st_pairs_events",
    lambda spark, d: _slots(spark, d).pairs().select(F.col("slot").cast("long").alias("slot"), F.col("l.event_id").alias("left_id"), F.col("r.event_id").alias("right_id")),
    f"SELECT slot, l AS left_id, r AS right_id FROM ({_SLOT_SQL})",
)
add(
    "st_sketch_events",
    lambda spark, d: _slots(spark, d).sketch(table(spark, d, "events").count(), 1, 0.1, 0.2, ["user_id", "event_type"]).hits([("user_id", ["user_id"]), ("event_type", ["event_type"])]),
    f"WITH p AS MATERIALIZED (SELECT a.user_id AS au, b.user_id AS bu, a.event_type AS ae, b.event_type AS be FROM ({_SLOT_SQL}) s JOIN events a ON a.event_id = s.l JOIN events b ON b.event_id = s.r)"
    " SELECT 'user_id' AS set_name, CAST(count(*) FILTER (WHERE au IS NOT DISTINCT FROM bu) AS BIGINT) AS hits FROM p UNION ALL SELECT 'event_type', CAST(count(*) FILTER (WHERE ae IS NOT DISTINCT FROM be) AS BIGINT) FROM p",
)

# -- built-in operators beside the library's

_COUNTED = ["l_orderkey", "l_partkey", "l_suppkey", "l_quantity"]


def _approximate(spark, d):
    """The built-in sketch of distinct values beside the exact count: within four standard errors of 2 %."""
    rows = table(spark, d, "lineitem")
    got = rows.agg(*[F.countDistinct(c).alias(c) for c in _COUNTED], *[F.approx_count_distinct(c, 0.02).alias(f"a_{c}") for c in _COUNTED])
    each = [F.struct(F.lit(c).alias("attr"), F.col(c).alias("groups"), (F.abs(F.col(f"a_{c}") - F.col(c)) <= 0.08 * F.col(c)).alias("close")) for c in _COUNTED]
    return got.select(F.explode(F.array(*each)).alias("x")).select("x.*")


add("op_approx_distinct_lineitem", _approximate, " UNION ALL ".join(f"SELECT '{c}' AS attr, CAST(count(DISTINCT {c}) AS BIGINT) AS groups, true AS close FROM lineitem" for c in _COUNTED))


def _bernoulli(spark, d):
    """The built-in Bernoulli sample has a random size; the bottom-rank sample has the size asked for."""
    rows = table(spark, d, "orders")
    got = rows.sample(False, 0.1, SEED).agg(F.count("*").alias("k")).crossJoin(rows.agg(F.count("*").alias("n")))  # one row each
    exactly = sampling.tuples(rows, 190, SEED, catalog.identity("orders")).count()
    return got.select("n", (F.abs(F.col("k") - 0.1 * F.col("n")) <= 6 * F.sqrt(0.09 * F.col("n"))).alias("bernoulli_close"), F.lit(exactly).cast("long").alias("bottom_rank"))


add("op_bernoulli_sample_orders", _bernoulli, "SELECT CAST(count(*) AS BIGINT) AS n, true AS bernoulli_close, CAST(190 AS BIGINT) AS bottom_rank FROM orders")


def _outside(spark, d):
    rows = table(spark, d, "orders").select("o_custkey", "o_orderpriority")
    urgent = table(spark, d, "orders").where("o_orderpriority = '1-URGENT'").select("o_custkey", "o_orderpriority")
    return rows.exceptAll(urgent).groupBy("o_orderpriority").agg(F.count("*").alias("k"))


add("op_except_all_orders", _outside, "SELECT o_orderpriority, CAST(count(*) AS BIGINT) AS k FROM (SELECT o_custkey, o_orderpriority FROM orders EXCEPT ALL SELECT o_custkey, o_orderpriority FROM orders WHERE o_orderpriority = '1-URGENT') GROUP BY 1")
add(
    "op_rollup_orders",
    lambda spark, d: table(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("k"), F.grouping_id().cast("long").alias("gid")),
    "SELECT o_orderstatus, o_orderpriority, CAST(count(*) AS BIGINT) AS k, CAST(grouping(o_orderstatus, o_orderpriority) AS BIGINT) AS gid FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
)
