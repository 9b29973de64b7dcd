"""What the given tables offer: row identities, named attribute sets, and the wide workloads, for Spark and as SQL text."""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sepkey.sources.stores import table

SEED = 42
EPS = 0.001

#: SQL expressions, valid in both engines, that identify a row. Doubles are taken as integer cents.
IDENTITY = {
    "lineitem": ["l_orderkey", "CAST(round(l_extendedprice * 100) AS BIGINT)"],
    "orders": ["o_orderkey"],
    "customer": ["c_custkey"],
    "supplier": ["s_suppkey"],
    "part": ["p_partkey"],
    "events": ["event_id"],
    "documents": ["doc_id"],
    "labels": ["doc_id"],
    "embeddings": ["vec_id"],
    "conversations": ["conv_id", "turn"],
    "signs": ["vec_id"],
    "flags": ["doc_id"],
    "nullable": ["o_orderkey"],
    "w1": ["o_orderkey"],
    "w2": ["l_orderkey", "CAST(round(l_extendedprice * 100) AS BIGINT)"],
}

ATTRIBUTES = {
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate".split(),
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority".split(),
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment".split(),
    "supplier": "s_suppkey s_name s_nationkey s_acctbal".split(),
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice".split(),
    "events": "event_id ts user_id event_type value props".split(),
    "documents": "doc_id text lang source n_chars".split(),
    "labels": "doc_id quality toxic".split(),
    "conversations": "conv_id turn role text".split(),
    "w1": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority c_name c_nationkey c_acctbal c_mktsegment n_name n_regionkey r_name".split(),
}

SETS = {
    "lineitem": [["l_linenumber"], ["l_returnflag", "l_linestatus"], ["l_quantity"], ["l_suppkey"], ["l_discount", "l_tax"], ["l_suppkey", "l_discount"], ["l_partkey"], ["l_shipdate"], ["l_quantity", "l_discount", "l_tax"], ["l_orderkey"], ["l_partkey", "l_quantity"], ["l_orderkey", "l_linenumber"], ["l_shipdate", "l_quantity"], ["l_partkey", "l_suppkey"], ["l_extendedprice"], ["l_orderkey", "l_extendedprice"]],
    "orders": [["o_orderkey"], ["o_custkey"], ["o_orderstatus"], ["o_totalprice"], ["o_orderdate"], ["o_orderpriority"], ["o_custkey", "o_orderdate"], ["o_custkey", "o_totalprice"], ["o_orderstatus", "o_orderpriority"]],
    "customer": [["c_custkey"], ["c_name"], ["c_nationkey"], ["c_acctbal"], ["c_mktsegment"], ["c_nationkey", "c_acctbal"], ["c_nationkey", "c_mktsegment"]],
    "supplier": [["s_suppkey"], ["s_nationkey"], ["s_acctbal"]],
    "part": [["p_partkey"], ["p_name"], ["p_brand"], ["p_type"], ["p_size"], ["p_retailprice"], ["p_size", "p_retailprice"], ["p_brand", "p_size"], ["p_name", "p_size", "p_retailprice"], ["p_brand", "p_type"]],
    "events": [["event_id"], ["user_id"], ["event_type"], ["props"], ["value"], ["user_id", "event_type"], ["user_id", "event_type", "value", "props"]],
    "labels": [["quality"], ["toxic"], ["quality", "toxic"], ["doc_id"]],
    "documents": [["text"], ["lang", "source"], ["source", "n_chars"], ["lang", "source", "n_chars"], ["text", "lang", "source", "n_chars"], ["doc_id"]],
    "conversations": [["conv_id"], ["turn"], ["conv_id", "role"], ["conv_id", "turn"]],
    "w1": [["o_orderkey"], ["o_totalprice"], ["o_orderdate"], ["o_custkey"], ["c_name"], ["c_acctbal"], ["c_nationkey"], ["o_orderpriority"], ["c_mktsegment"], ["n_regionkey"], ["o_orderstatus"], ["o_custkey", "o_orderdate"], ["c_nationkey", "o_orderdate"]],
}


def named(sets: list[list[str]]) -> list[tuple[str, list[str]]]:
    """(name, attributes), each set once whatever the order of its attributes."""
    seen, out = set(), []
    for attrs in sets:
        if frozenset(attrs) not in seen:
            seen.add(frozenset(attrs))
            out.append((",".join(attrs), list(attrs)))
    return out


def random_sets(attrs: list[str], count: int = 100, seed: int = SEED, smallest: int = 1, largest: int | None = None) -> list[list[str]]:
    """Distinct random sets, their sizes uniform in smallest..largest; fewer where there are not that many."""
    rng = random.Random(seed)
    largest = min(largest or len(attrs), len(attrs))
    out: dict[frozenset, list[str]] = {}
    for _ in range(count * 20):
        chosen = rng.sample(range(len(attrs)), rng.randint(smallest, largest))
        attrs_of = [attrs[i] for i in sorted(chosen)]
        out.setdefault(frozenset(attrs_of), attrs_of)
        if len(out) == count:
            break
    return list(out.values())


def identity(name: str) -> list[Column]:
    return [F.expr(e) for e in IDENTITY[name]]


# -- joins of the wide workloads

W1_SQL = """SELECT o_orderkey, o_custkey, o_orderstatus, o_totalprice, o_orderdate, o_orderpriority, c_name, c_nationkey, c_acctbal, c_mktsegment,
 n_name, n_regionkey, r_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""


def w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """orders with customer, nation and region: 13 columns. Sizes of the joins are left to the optimiser."""
    o, c, n, r = (table(spark, sf_dir, x) for x in ("orders", "customer", "nation", "region"))
    wide = o.join(c, o.o_custkey == c.c_custkey).join(n, F.col("c_nationkey") == n.n_nationkey).join(r, F.col("n_regionkey") == r.r_regionkey)
    return wide.select(*ATTRIBUTES["w1"])


W2_MODULI = (None, 97, 31, 7, 2)
W3_MODULI = (None, 1009, 251, 97, 53, 31, 17, 11, 7, 5, 3, 2)
_STRINGS = {"l_returnflag", "l_linestatus", "o_orderstatus", "o_orderpriority", "c_name", "c_mktsegment", "n_name", "r_name", "p_name", "p_brand", "p_type", "s_name"}
_MONEY = {"l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "c_acctbal", "p_retailprice", "s_acctbal"}
_DATES = {"l_shipdate", "o_orderdate"}
W3_COLUMNS = ATTRIBUTES["lineitem"] + ATTRIBUTES["orders"][1:] + ATTRIBUTES["customer"][1:] + ["n_name", "n_regionkey", "r_name"] + ATTRIBUTES["part"][1:] + ATTRIBUTES["supplier"][1:]


def code_sql(column: str, engine: str) -> str:
    """A BIGINT code of a column: cents, days since 1970, the head of an MD5, or the number itself."""
    if column in _STRINGS:
        return f"CAST(conv(substr(md5({column}), 1, 15), 16, 10) AS BIGINT)" if engine == "spark" else f"CAST(concat('0x', substr(md5({column}), 1, 15)) AS BIGINT)"
    if column in _DATES:
        return f"CAST(datediff(CAST({column} AS DATE), DATE'1970-01-01') AS BIGINT)" if engine == "spark" else f"CAST(date_diff('day', DATE '1970-01-01', CAST({column} AS DATE)) AS BIGINT)"
    if column in _MONEY:
        return f"CAST(round({column} * 100) AS BIGINT)"
    return f"CAST({column} AS BIGINT)"


def coarse_columns(columns: list[str], moduli: tuple, engine: str) -> list[tuple[str, str]]:
    """(name, SQL): each column's code, and its remainder by each modulus."""
    out = []
    for c in columns:
        code = code_sql(c, engine)
        for b in moduli:
            if b is None:
                out.append((f"{c}_code", code))
            else:
                out.append((f"{c}_m{b}", f"pmod({code}, {b})" if engine == "spark" else f"((({code}) % {b}) + {b}) % {b}"))
    return out


W2_ATTRIBUTES = [n for n, _ in coarse_columns(ATTRIBUTES["lineitem"], W2_MODULI, "spark")]


def w2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem as 55 integer columns beside its identity columns."""
    rows = table(spark, sf_dir, "lineitem")
    return rows.select("l_orderkey", "l_extendedprice", *[F.expr(e).alias(n) for n, e in coarse_columns(ATTRIBUTES["lineitem"], W2_MODULI, "spark")])


W2_SQL = "SELECT l_orderkey, l_extendedprice, " + ", ".join(f"{e} AS {n}" for n, e in coarse_columns(ATTRIBUTES["lineitem"], W2_MODULI, "duckdb")) + " FROM lineitem"


def w3_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star join of all seven tables as 31 integer codes, beside the identity columns. Samples are drawn from this; the 12 grades of a code are
    made of sampled rows only, as they follow from it."""
    names = ("lineitem", "orders", "customer", "nation", "region", "part", "supplier")
    li, o, c, n, r, p, s = (table(spark, sf_dir, x) for x in names)
    wide = li.join(o, li.l_orderkey == o.o_orderkey).join(c, F.col("o_custkey") == c.c_custkey).join(n, F.col("c_nationkey") == n.n_nationkey).join(r, F.col("n_regionkey") == r.r_regionkey)
    wide = wide.join(p, F.col("l_partkey") == p.p_partkey).join(s, F.col("l_suppkey") == s.s_suppkey)
    return wide.select("l_orderkey", "l_extendedprice", *[F.expr(code_sql(x, "spark")).alias(f"{x}_code") for x in W3_COLUMNS])


def w3_grades(codes: DataFrame) -> DataFrame:
    """All 372 columns of rows of ``w3_codes``."""
    return codes.select(*[(F.col(f"{c}_code") if b is None else F.pmod(f"{c}_code", F.lit(b))).alias(f"{c}_code" if b is None else f"{c}_m{b}") for c in W3_COLUMNS for b in W3_MODULI])


W3_ATTRIBUTES = [n for n, _ in coarse_columns(W3_COLUMNS, W3_MODULI, "spark")]


#: orders with nulls, NaN and integers beyond 2^53: ``wide`` is a key, and so is ``wide_null``, one of whose values is null.
_NULLABLE = {
    "o_orderkey": "o_orderkey",
    "cust": "CASE WHEN o_orderkey % 10 = 0 THEN NULL ELSE o_custkey END",
    "price": "CASE WHEN o_orderkey % 3 = 0 THEN NULL ELSE o_totalprice END",
    "nan_price": "CASE WHEN o_orderkey % 5 = 0 THEN CAST('NaN' AS DOUBLE) WHEN o_orderkey % 5 = 1 THEN NULL ELSE o_totalprice END",
    "status": "CASE WHEN o_orderkey % 2 = 0 THEN NULL ELSE o_orderstatus END",
    "wide": "o_orderkey + 9007199254740992",
    "wide_null": "CASE WHEN o_orderkey = 1 THEN NULL ELSE o_orderkey + 9007199254740992 END",
}
ATTRIBUTES["nullable"] = list(_NULLABLE)[1:]
ATTRIBUTES["signs"] = [f"d{i}" for i in range(64)]
FLAG_WORDS = ("the", "and", "der", "die", "que", "les", "una")
ATTRIBUTES["flags"] = ["lang", "source", "size_bucket", *[f"has_{w}" for w in FLAG_WORDS], "quality", "toxic"]

NULLABLE_SQL = "SELECT " + ", ".join(f"{e} AS {n}" for n, e in _NULLABLE.items()) + " FROM orders"
SIGNS_SQL = "SELECT vec_id, label, " + ", ".join(f"CAST(embedding[{i + 1}] > 0 AS INTEGER) AS d{i}" for i in range(64)) + " FROM embeddings"
FLAGS_SQL = (
    "SELECT d.doc_id, lang, source, floor(log2(n_chars + 1)) AS size_bucket, "
    + ", ".join(f"contains(concat(' ', lower(coalesce(text, '')), ' '), ' {w} ') AS has_{w}" for w in FLAG_WORDS)
    + ", quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id"
)


def nullable(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(*[F.expr(e).alias(n) for n, e in _NULLABLE.items()])


def source(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    made = {"w1": w1, "w2": w2, "nullable": nullable, "signs": embedding_signs, "flags": document_flags}
    return made[name](spark, sf_dir) if name in made else table(spark, sf_dir, name)


def source_sql(name: str) -> str:
    return {"w1": W1_SQL, "w2": W2_SQL, "nullable": NULLABLE_SQL, "signs": SIGNS_SQL, "flags": FLAGS_SQL}.get(name, f"SELECT * FROM {name}")


def attributes(name: str) -> list[str]:
    return {"w2": W2_ATTRIBUTES, "w3": W3_ATTRIBUTES}.get(name) or ATTRIBUTES[name]


def embedding_signs(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    """vec_id, label and one 0/1 column for the sign of each dimension."""
    e = table(spark, sf_dir, "embeddings")
    return e.select("vec_id", "label", *[(F.element_at("embedding", i + 1) > 0).cast("int").alias(f"d{i}") for i in range(dims)])


def document_flags(spark: SparkSession, sf_dir: str, words: tuple[str, ...] = FLAG_WORDS) -> DataFrame:
    """doc_id, language, source, a length bucket, word-presence flags, and the labels where there are any."""
    d, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    padded = F.concat(F.lit(" "), F.lower(F.coalesce("text", F.lit(""))), F.lit(" "))
    flags = d.select("doc_id", "lang", "source", F.floor(F.log2(F.col("n_chars") + 1)).alias("size_bucket"), *[F.contains(padded, F.lit(f" {w} ")).alias(f"has_{w}") for w in words])
    return flags.join(labels, "doc_id", "left")
