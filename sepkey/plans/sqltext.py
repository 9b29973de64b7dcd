"""SQL for other engines that computes what the registered queries compute, from the same definitions."""

from __future__ import annotations

from itertools import combinations

from sepkey.functions import portable
from sepkey.plans import catalog

Sets = list[tuple[str, list[str]]]


def gamma(src: str, sets: Sets) -> str:
    return " UNION ALL ".join(
        f"SELECT '{n}' AS set_name, CAST(sum(k) AS BIGINT) AS n, CAST(sum(k * (k - 1) // 2) AS BIGINT) AS gamma, CAST(count(*) AS BIGINT) AS groups, CAST(max(k) AS BIGINT) AS max_group"
        f" FROM (SELECT count(*) AS k FROM {src}{' GROUP BY ' + ', '.join(a) if a else ''})"
        for n, a in sets
    )


def with_ppb(sql: str) -> str:
    return f"SELECT *, CAST(floor(CAST(gamma AS DOUBLE) / (CAST(n * (n - 1) // 2 AS DOUBLE)) * 1e9) AS BIGINT) AS together_ppb FROM ({sql})"


def verdicts(src: str, sets: Sets, eps: float) -> str:
    return f"SELECT set_name, gamma, CASE WHEN gamma = 0 THEN 'key' WHEN CAST(gamma AS DOUBLE) <= {eps} * CAST(n * (n - 1) // 2 AS DOUBLE) THEN 'slack' ELSE 'bad' END AS verdict FROM ({gamma(src, sets)})"


def tuple_sample(name: str, r: int, seed: int = catalog.SEED) -> str:
    ids = catalog.IDENTITY[name]
    return f"(SELECT * FROM ({catalog.source_sql(name)}) ORDER BY {portable.sql_rank(seed, ids)}, {', '.join(ids)} LIMIT {r})"


def tuple_accepts(name: str, sets: Sets, r: int, seed: int = catalog.SEED) -> str:
    body = " UNION ALL ".join(f"SELECT '{n}' AS set_name, NOT EXISTS (SELECT 1 FROM s GROUP BY {', '.join(a)} HAVING count(*) > 1) AS accept" for n, a in sets)
    return f"WITH s AS MATERIALIZED {tuple_sample(name, r, seed)} {body}"


def ordinals(name: str) -> str:
    return f"(SELECT *, row_number() OVER (ORDER BY {', '.join(catalog.IDENTITY[name])}) - 1 AS ordinal FROM ({catalog.source_sql(name)}))"


def pair_draws(name: str, s: int, seed: int = catalog.SEED) -> str:
    n = "(SELECT count(*) FROM o)"
    i = f"{portable.sql_draw(seed, 't', 'i')} % {n}"
    j = f"{portable.sql_draw(seed, 't', 'j')} % ({n} - 1)"
    return f"(SELECT t AS slot, i, j0 + CASE WHEN j0 >= i THEN 1 ELSE 0 END AS j FROM (SELECT t, {i} AS i, {j} AS j0 FROM (SELECT range AS t FROM range({s}))))"


def pair_flags(name: str, attrs: list[str], s: int, seed: int = catalog.SEED) -> str:
    """CTEs o, d and p: ordinals, draws and flags (agrees) for each pair."""
    flags = ", ".join(f"(l.{a} IS NOT DISTINCT FROM r.{a}) AS {a}" for a in attrs)
    return f"o AS MATERIALIZED {ordinals(name)}, d AS MATERIALIZED {pair_draws(name, s, seed)}, p AS MATERIALIZED (SELECT d.slot, {flags} FROM d JOIN o l ON l.ordinal = d.i JOIN o r ON r.ordinal = d.j)"


def pair_accepts(name: str, attrs: list[str], sets: Sets, s: int, seed: int = catalog.SEED) -> str:
    body = " UNION ALL ".join(f"SELECT '{n}' AS set_name, NOT coalesce(bool_or({' AND '.join(a)}), false) AS accept FROM p" for n, a in sets)
    return f"WITH {pair_flags(name, attrs, s, seed)} {body}"


def hits(name: str, attrs: list[str], sets: Sets, s: int, seed: int = catalog.SEED) -> str:
    body = " UNION ALL ".join(f"SELECT '{n}' AS set_name, CAST(count(*) FILTER (WHERE {' AND '.join(a)}) AS BIGINT) AS hits FROM p" for n, a in sets)
    return f"WITH {pair_flags(name, attrs, s, seed)} {body}"


def both_filters(name: str, attrs: list[str], sets: Sets, r: int, s: int, seed: int = catalog.SEED) -> str:
    t = f"SELECT * FROM ({tuple_accepts(name, sets, r, seed)})"
    p = f"SELECT * FROM ({pair_accepts(name, attrs, sets, s, seed)})"
    return f"SELECT a.set_name, a.accept AS tuple_accept, b.accept AS pair_accept FROM ({t}) a JOIN ({p}) b USING (set_name)"


def trace_ctes(src: str, attrs: list[str], steps: int = 6, first: tuple[str, ...] = ()) -> str:
    """CTEs p1, p2, ... (attr, gamma) of greedy refinement, a few for each step; ``first``: attributes taken before any choice."""
    cells = " UNION ALL ".join(f"SELECT rid, '{a}' AS attr, {i} AS ord, coalesce(CAST({a} AS VARCHAR), '~null') AS v FROM b" for i, a in enumerate(attrs))
    out = [
        f"b AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM {src})",
        f"cells AS MATERIALIZED ({cells})",
        "st0 AS (SELECT rid, '' AS cls FROM b)",
        "p0 AS (SELECT '' AS attr, CAST(count(*) * (count(*) - 1) // 2 AS BIGINT) AS gamma FROM b)",
    ]
    for k in range(1, steps + 1):
        used = " UNION ALL ".join(f"SELECT attr FROM p{j}" for j in range(k))
        counted = f"SELECT cls, attr, ord, v, count(*) AS c FROM st{k - 1} JOIN cells USING (rid) GROUP BY ALL"
        out.append(f"g{k} AS MATERIALIZED (SELECT attr, ord, CAST(sum(c * (c - 1) // 2) AS BIGINT) AS gamma FROM ({counted}) GROUP BY ALL)")
        if k <= len(first):
            out.append(f"p{k} AS MATERIALIZED (SELECT attr, gamma FROM g{k} WHERE attr = '{first[k - 1]}' AND (SELECT gamma FROM p{k - 1}) > 0)")
        else:
            best = f"SELECT * FROM g{k} WHERE attr NOT IN ({used}) ORDER BY gamma, ord LIMIT 1"
            out.append(f"p{k} AS MATERIALIZED (SELECT attr, gamma FROM ({best}) WHERE gamma < (SELECT gamma FROM p{k - 1}))")
        out.append(f"st{k} AS MATERIALIZED (SELECT rid, concat(cls, '|', v) AS cls FROM st{k - 1} JOIN cells USING (rid) WHERE attr = (SELECT attr FROM p{k}))")
    return ", ".join(out)


def greedy_trace(src: str, attrs: list[str], steps: int = 6, first: tuple[str, ...] = ()) -> str:
    """step, attr, gamma_after."""
    body = " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS step, attr, gamma AS gamma_after FROM p{k}" for k in range(1, steps + 1))
    return f"WITH {trace_ctes(src, attrs, steps, first)} {body}"


def found_gamma(src: str, sample: str, attrs: list[str], steps: int = 6) -> str:
    """attrs, size, n, gamma: what the greedy key of a sample leaves together among all rows."""
    picks = " UNION ALL ".join(f"SELECT {k} AS step, attr FROM p{k}" for k in range(1, steps + 1))
    cells = ", ".join(f"CASE WHEN list_contains((SELECT names FROM picked), '{a}') THEN coalesce(CAST({a} AS VARCHAR), '~null') END AS c{i}" for i, a in enumerate(attrs))
    return (
        f"WITH {trace_ctes(sample, attrs, steps)}, picked AS MATERIALIZED (SELECT list(attr ORDER BY step) AS names FROM ({picks})),"
        f" cells_of AS (SELECT {cells} FROM {src}), counted AS (SELECT count(*) AS k FROM cells_of GROUP BY {', '.join(f'c{i}' for i in range(len(attrs)))})"
        f" SELECT array_to_string((SELECT names FROM picked), ',') AS attrs, CAST((SELECT len(names) FROM picked) AS BIGINT) AS size,"
        f" CAST(sum(k) AS BIGINT) AS n, CAST(sum(k * (k - 1) // 2) AS BIGINT) AS gamma FROM counted"
    )


def pair_trace(ctes: str, attrs: list[str], steps: int = 6) -> str:
    """step, attr, gamma_after: greedy cover of the pairs in CTE p (flags: agrees)."""
    out = [ctes, "q0 AS (SELECT * FROM p)", "w0 AS (SELECT '' AS attr, count(*) AS left_over FROM p)"]
    for k in range(1, steps + 1):
        used = " UNION ALL ".join(f"SELECT attr FROM w{j}" for j in range(k))
        counts = " UNION ALL ".join(f"SELECT '{a}' AS attr, {i} AS ord, count(*) FILTER (WHERE NOT {a}) AS c FROM q{k - 1}" for i, a in enumerate(attrs))
        out.append(f"w{k} AS MATERIALIZED (SELECT attr, (SELECT left_over FROM w{k - 1}) - c AS left_over FROM ({counts}) WHERE c > 0 AND attr NOT IN ({used}) ORDER BY c DESC, ord LIMIT 1)")
        pick = " ".join(f"WHEN '{a}' THEN {a}" for a in attrs)
        out.append(f"q{k} AS MATERIALIZED (SELECT * FROM q{k - 1} WHERE CASE (SELECT attr FROM w{k}) {pick} ELSE false END)")
    return "WITH " + ", ".join(out) + " " + " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS step, attr, CAST(left_over AS BIGINT) AS gamma_after FROM w{k}" for k in range(1, steps + 1))


def first_smallest(tests: list[tuple[int, int, str, str]], ctes: str = "") -> str:
    """attrs, size: the first set of the smallest size whose test holds. tests: (size, order, name, SQL boolean)."""
    body = " UNION ALL ".join(f"SELECT {size} AS size, {i} AS ord, '{n}' AS attrs, {test} AS ok" for size, i, n, test in tests)
    return f"{ctes} SELECT attrs, CAST(size AS BIGINT) AS size FROM ({body}) WHERE ok ORDER BY size, ord LIMIT 1"


def subsets(attrs: list[str], largest: int) -> list[tuple[int, int, list[str]]]:
    return [(size, i, list(c)) for size in range(1, largest + 1) for i, c in enumerate(combinations(attrs, size))]
