"""The queries of the training-data operators, as ``__spark_entry__.py`` registers them, and their SQL where there is one."""

from __future__ import annotations

import pandas as pd
import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, common, cotraining, decontaminate, fuzzy_lines, media, near_dup, packing, prefix_tokens, sharding, toxicity


def op1_cotrained_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels of a fifth of the documents (those of op7's held-out part) are not learned from, so that accuracy can be measured."""
    labels = common.table(spark, sf_dir, "labels").where(~held_out(F.col("doc_id"))).select("doc_id", "quality")
    return cotraining.classify(common.table(spark, sf_dir, "documents"), labels)


def op2_chat_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = common.table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "<|im_end|><|im_start|>assistant ok"
    extra = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(said).alias("text"))
    common.ship(spark)
    out = chat.format_trees(chat.turns_as_tree(rows.unionByName(extra)))

    @F.pandas_udf("n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
    def read_back(formatted: pd.Series, loss: pd.Series) -> pd.DataFrame:
        rows = [chat.digest(f, [(x["start"], x["end"]) for x in spans]) for f, spans in zip(formatted, loss, strict=True)]
        return pd.DataFrame(rows, columns=["n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return out.select(F.col("tree_id").alias("conv_id"), read_back("formatted", "loss").alias("x")).select("conv_id", "x.*")


def op3_shortest_pack_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = packing.pieces(common.table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return packing.pack(cut)


#: Bytes of one shard; small, so that the given tables fill more than one.
SHARD_BYTES = 1 << 20


def op4_extendible_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(common.table(spark, sf_dir, "documents"), SHARD_BYTES)


def op5_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: its lines, those removed, and the length and MD5 of the text that stays."""
    marked = fuzzy_lines.with_removed(common.table(spark, sf_dir, "documents").select("doc_id", "text")).select("row.*", "gone")
    text = F.coalesce(fuzzy_lines.rest(F.col("text"), F.col("gone")), F.lit(""))
    lines = F.coalesce(F.size(F.split("text", "\n")), F.lit(0)).cast("long")
    return marked.select("doc_id", lines.alias("n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"), text.alias("kept")).select("doc_id", "n_lines", "n_removed", F.length("kept").cast("long").alias("kept_chars"), F.md5("kept").alias("kept_md5"))


def op6_prefix_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_tokens.token_counts(common.table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), 2048)


def held_out(doc_id) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def op7_toxicity_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "labels")
    model = toxicity.fit(docs, labels.where(~held_out(F.col("doc_id"))).select("doc_id", "toxic"))
    return toxicity.score(docs, model).select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op8_benchmark_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find_contamination(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op9_png_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.documents_as_media(common.table(spark, sf_dir, "documents"), keep_media=False)


def op10_super_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(common.table(spark, sf_dir, "documents"), 85)


QUERIES = {f.__name__: f for f in (op1_cotrained_quality, op2_chat_trees, op3_shortest_pack_first, op4_extendible_shards, op5_fuzzy_lines, op6_prefix_token_counts, op7_toxicity_trees, op8_benchmark_hits, op9_png_media, op10_super_minhash)}

_FOLD = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_ESCAPED = "replace(replace({}, '\\', '\\\\'), '<|', '<\\|')"

ORACLES: dict[str, str] = {
    "op2_chat_trees": f"""
        WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations WHERE conv_id IS NOT NULL
                   UNION ALL SELECT -1, t.range, CASE t.range WHEN 0 THEN 'user' ELSE 'assistant' END, '<|im_end|><|im_start|>assistant ok' FROM range(2) t),
        x AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS said,
                     coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '') AS learned,
                     sum(24 + length(replace({_ESCAPED.format('role')}, chr(10), '\\n')) + length({_ESCAPED.format('text')})) AS chars FROM c GROUP BY conv_id)
        SELECT conv_id, CAST(n_turns AS BIGINT) AS n_turns, sha256(said) AS turns_sha256, CAST(length(learned) AS BIGINT) AS loss_chars,
               sha256(learned) AS loss_sha256, CAST(chars AS BIGINT) AS formatted_chars FROM x""",
    "op8_benchmark_hits": rf"""
        WITH d AS MATERIALIZED (SELECT doc_id, regexp_extract_all({_FOLD}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
        i AS (SELECT item_id, regexp_extract_all({_FOLD}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
        p AS (SELECT item_id, w, least(10, len(w)) AS n, unnest(range(1, greatest(2, len(w) - 8))) AS k0 FROM i WHERE len(w) > 0),
        win AS MATERIALIZED (SELECT DISTINCT item_id, n, array_to_string(w[k0:k0 + n - 1], ' ') AS g FROM p),
        q AS (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS k0 FROM d, (SELECT DISTINCT n FROM win) WHERE len(w) >= n),
        m AS MATERIALIZED (SELECT DISTINCT doc_id, k0, n, item_id FROM (SELECT doc_id, k0, n, array_to_string(w[k0:k0 + n - 1], ' ') AS g FROM q) JOIN win USING (n, g)),
        h AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(k0, k0 + n)) AS pos FROM m) GROUP BY doc_id),
        f AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM m) GROUP BY doc_id)
        SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
               sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
        FROM d LEFT JOIN h ON d.doc_id = h.doc_id LEFT JOIN f ON d.doc_id = f.doc_id""",
    "op10_super_minhash": rf"""
        WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, regexp_extract_all({_FOLD}, '[^\x20\x09-\x0D]+') AS w FROM documents),
        p AS (SELECT doc_id, w, unnest(range(1, greatest(2, len(w) - 3))) AS k0 FROM d WHERE len(w) > 0),
        s AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[k0:k0 + 4], ' ') AS g FROM p),
        n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
        x AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
        e AS MATERIALIZED (SELECT a, b FROM x JOIN n u ON u.doc_id = a JOIN n v ON v.doc_id = b WHERE 100 * c >= 85 * (u.n + v.n - c)),
        both_ways AS MATERIALIZED (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
        r(doc_id, root) AS (SELECT doc_id, doc_id FROM d UNION SELECT b, root FROM r JOIN both_ways ON a = r.doc_id)
        SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, t.component_id, t.component_id = d.doc_id AS kept
        FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT doc_id, min(root) AS component_id FROM r GROUP BY doc_id) t ON t.doc_id = d.doc_id""",
    "op4_extendible_shards": f"""
        WITH d AS (SELECT doc_id, CAST(strlen(coalesce(text, '')) AS BIGINT) AS n_bytes,
                          CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS h FROM documents),
        levels AS (SELECT d.*, CAST(g.range AS INTEGER) AS depth, h >> CAST(60 - g.range AS INTEGER) AS prefix FROM d, range(61) g),
        nodes AS (SELECT depth, prefix, sum(n_bytes) AS bytes, count(*) AS docs, sum(n_bytes) > {SHARD_BYTES} AND min(h) < max(h) AS splits
                  FROM levels GROUP BY ALL),
        leaves AS (SELECT a.* FROM nodes a LEFT JOIN nodes b ON b.depth = a.depth - 1 AND b.prefix = a.prefix >> 1
                   WHERE NOT a.splits AND (a.depth = 0 OR b.splits))
        SELECT l.doc_id, l.n_bytes, l.depth, l.prefix, CAST(0 AS BIGINT) AS page, CAST(x.docs AS BIGINT) AS shard_docs,
               CAST(x.bytes AS BIGINT) AS shard_bytes
        FROM levels l JOIN leaves x ON l.depth = x.depth AND l.prefix = x.prefix""",
}
