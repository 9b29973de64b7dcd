"""Deduplication of fuzzy lines, with DataFrame functions only.

A line is normalised to its lower-case words (digits, ASCII letters and all characters beyond ASCII) with one blank between; lines of one
normalised form are one node (by a 64-bit hash). Two nodes are linked if the edit similarity of the normalised lines, 1 - edits / longer length, is
at least the threshold; nothing else decides. Of each connected group the occurrence with the smallest (doc_id, line number) stays.

Candidates come from SimHash. The votes are sparse: each distinct word votes on the bits of one block only, the one its hash deals it to. A line that
differs from another in a few words therefore agrees with it on every block that none of these words is dealt to, however many bits differ
elsewhere, and a join on blocks (on pairs of blocks where lines are short) finds it. Longer lines have more blocks, of which ``KEPT`` are used, so
that a block always holds the votes of some two to five words; blocks of fewer than ``LEAST`` make no key. Where a line has ``MANY`` words of ``LONG``
letters or more, only these vote; where it has ``ENOUGH`` but not so many, it is looked up both ways. Lines of at most ``FEW`` words have keys for all
words but one besides.

Of lines that meet, 256 bits say which words they have (a bit a word). Unlike bits never outnumber unlike words, so a pair of which more than
``UNLIKE`` of 100 words are surely in one line only is dropped (pairs of fewer than ``ASKED`` words are not asked); edit similarity judges the rest.

Votes are sums of counters over the words of a block. Lines are dealt by node before their words are laid out, so that these sums, unlike a group-by of
words, move no word: the words of a line stay in its task.

A pair is missed if each block has a word that differs; the tests and the README give the recall against edit similarity alone. Lines of one
word, and those whose edits lie in nearly all words, are matched by equality alone. Lines without words always stay (blank lines, brackets, rules).

Rows without doc_id pass unchanged; repeated rows count once and get the same result; of different texts under one doc_id each keeps or loses
its own lines. Null texts are empty and stay null. Extra columns, whatever their names, are kept by ``dedup`` and ignored by ``decide``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common, grouping

PERCENT = 80
LONG, ENOUGH, MANY = 4, 5, 8
#: Most voting words of lines whose every word is a block of its own as well: a key leaves out one of them, or none.
FEW = 8
KEPT = 10
#: Of 100 words of both lines together, those that may surely lie in one of them only; pairs of fewer than ``ASKED`` words are compared in any case.
UNLIKE, ASKED = 30, 28
#: Fewest words whose votes make a key.
LEAST = 3
#: Fewest words of the levels above the first. At level 0 a key is a pair of 5 blocks, at level 1 one of 6 blocks, to which words are dealt twice over; level 2 + i begins at 28 * 2^i
#: words and has 12 * 2^i - 1 blocks. Word counts within ``MARGIN`` of a border belong to both levels.
LEVEL_1, LEVEL_2 = 14, 28
MARGIN = 1.1
#: Lines of a part, whose words and blocks one task holds at a time.
PART = 50_000


#: A run of what is no word character, other than one blank alone; line ends stay.
_GAP = r"[\x00-\x09\x0b-\x1f\x21-\x2f\x3a-\x60\x7b-\x7f][\x00-\x09\x0b-\x2f\x3a-\x60\x7b-\x7f]*| [\x00-\x09\x0b-\x2f\x3a-\x60\x7b-\x7f]+"


def _norms(text: Column) -> Column:
    """The lines of a text in normal form but for a blank at either end."""
    return F.split(F.regexp_replace(F.lower(text), _GAP, " "), "\n")


#: A place is a number made of the doc_id, 20 bits of the text's hash (for texts that share a doc_id) and the line number.
_LINES, _TEXTS = 1 << 31, 1 << 20


def _identified(docs: DataFrame) -> DataFrame:
    """doc_id, variant, text of the rows that have lines."""
    return docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), _variant().alias("variant"), "text")


def _variant() -> Column:
    return F.pmod(F.xxhash64("text"), F.lit(_TEXTS)).cast("int")


def _place() -> Column:
    """One number for an occurrence: unlike a struct, its minimum is kept in place by hash aggregates."""
    text = (F.col("doc_id").cast("decimal(19,0)") * F.lit(_TEXTS).cast("decimal(7,0)") + F.col("variant")).cast("decimal(27,0)")
    return (text * F.lit(_LINES).cast("decimal(10,0)") + F.col("line_no")).cast("decimal(38,0)")


def lines_of(docs: DataFrame) -> DataFrame:
    """doc_id, variant, line_no, node, norm of all lines that have words."""
    each = _identified(docs).select("doc_id", "variant", F.posexplode(_norms(F.col("text"))).alias("line_no", "line"))
    return each.select("doc_id", "variant", "line_no", F.trim("line").alias("norm")).where("norm <> ''").withColumn("node", F.xxhash64("norm"))


#: Fixed value: fifteen counters of four bits.
_ONES = 0x0111111111111111
#: The pairs of the five blocks of level 0, by number, that each block is in.
_PAIRS = [[i for i, p in enumerate((p, q) for p in range(5) for q in range(p + 1, 5)) if b in p] for b in range(5)]


def _level(n: Column) -> Column:
    return F.when(n < LEVEL_1, 0).when(n < LEVEL_2, 1).otherwise(2 + F.floor(F.log2(n / LEVEL_2))).cast("int")


def _majority(n: Column, votes: list[Column]) -> Column:
    """30 bits, each that of most of the n hashes whose votes were summed. A counter holds up to 15; what a fuller block carries over makes another,
    equally fixed, value."""
    over = F.greatest(F.lit(0), 7 - F.floor(n / 2)).cast("long") * F.lit(_ONES)
    bits = [F.shiftleft(F.shiftrightunsigned((v + over).bitwiseAND(F.lit(_ONES * 8)), 3), j) for j, v in enumerate(votes)]
    return bits[0].bitwiseOR(bits[1])


def _parts(lines: DataFrame) -> int:
    return 1 + lines.count() // PART


def keys(lines: DataFrame) -> DataFrame:
    """(bucket, node) for each key of each line (none: equality only)."""
    each = lines.select("node", "norm").repartition(_parts(lines), "node").distinct()
    each = each.select("node", F.array_distinct(F.split("norm", " ")).alias("w"))
    each = each.withColumn("long", F.filter("w", lambda w: F.length(w) >= LONG))
    long = F.size("long")
    ways = F.when(long >= MANY, F.array("long")).when((long >= ENOUGH) & (long < F.size("w")), F.array("w", "long")).otherwise(F.array("w"))
    each = each.select("node", F.explode(ways).alias("w")).select("node", "w", F.size("w").alias("n")).where("n > 1")
    # level -1: each text is a key, the words of a short line in order, whole or but for one
    order = F.array_sort("w")
    but_one = F.when(F.col("n") > 2, F.transform("w", lambda x: F.array_join(F.array_remove(order, x), " "))).otherwise(F.array().cast("array<string>"))
    few = F.when(F.col("n") <= FEW, F.array(F.struct(F.lit(-1).alias("level"), F.concat(F.array(F.array_join(order, " ")), but_one).alias("w"))))
    levels = F.array_distinct(F.array(_level(F.col("n") / MARGIN), _level(F.col("n") * MARGIN)))
    dealt = F.transform(levels, lambda x: F.struct(x.alias("level"), F.col("w")))
    each = each.select("node", "n", F.explode(F.concat(F.coalesce(few, F.array().cast("array<struct<level:int,w:array<string>>>")), dealt)).alias("x"))
    word = each.select("node", "n", F.col("x.level").alias("level"), F.col("x.w").alias("w")).select("node", "n", "level", F.explode("w").alias("word"))
    level = F.col("level")
    blocks = F.when(level < 1, 5).when(level < 2, 6).otherwise(F.call_function("shiftleft", F.lit(12).cast("long"), level - 2) - 1).cast("long")
    word = word.select("node", "n", "level", F.xxhash64("word").alias("h"), blocks.alias("blocks"))
    word = word.withColumn("block", F.when(level < 0, F.col("h")).otherwise(F.pmod(F.xxhash64("h"), F.col("blocks")))).where((level < 0) | (F.col("block") < KEPT))
    pairs = F.array(*[F.array(*[F.lit(i).cast("long") for i in p]) for p in _PAIRS])
    again = 6 + F.pmod(F.xxhash64("h", F.lit(1)), F.lit(6).cast("long"))
    word = word.select("node", "n", "level", "h", F.explode(F.when(level == 0, F.get(pairs, F.col("block").cast("int"))).when(level == 1, F.array("block", again)).otherwise(F.array("block"))).alias("block"))
    word = word.select("node", "n", F.xxhash64("level", "block").alias("cell"), F.when(level < 0, LEAST).otherwise(1).alias("one"), *[F.shiftrightunsigned("h", j).bitwiseAND(F.lit(_ONES)).alias(f"v{j}") for j in range(2)])
    full = word.groupBy("node", "n", "cell").agg(F.sum("one").alias("size"), F.sum("v0").alias("v0"), F.sum("v1").alias("v1")).where(F.col("size") >= LEAST)
    return full.select(F.xxhash64("cell", "size", _majority(F.col("size"), [F.col("v0"), F.col("v1")])).alias("bucket"), "node")


def _shared(lines: DataFrame) -> DataFrame:
    """The keys that two nodes or more have, once for each node."""
    dealt = keys(lines).repartition(_parts(lines), "bucket")
    shared = dealt.groupBy("bucket").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("bucket")
    # an inner join: a semi-join would be pushed below the exchange, which then could not be used twice
    return dealt.join(shared.hint("shuffle_hash"), "bucket").distinct()


def _texts(lines: DataFrame, wanted: DataFrame) -> DataFrame:
    """(node, norm) of the nodes ``wanted``."""
    return lines.join(common.small(wanted, F.lit(16)), "node", "left_semi").groupBy("node", "norm").agg(F.lit(1).alias("one")).select("node", "norm")


def _marked(texts: DataFrame) -> DataFrame:
    """node, length (characters), n_words, and 256 bits that say which words there are."""
    word = texts.select("node", F.length("norm").alias("length"), F.explode(F.array_distinct(F.split("norm", " "))).alias("word")).select("node", "length", F.xxhash64("word").alias("h"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("h").bitwiseAND(F.lit(63)).cast("int"))
    lane = F.shiftrightunsigned("h", 6).bitwiseAND(F.lit(3))
    return word.groupBy("node", "length").agg(F.count("*").cast("int").alias("n_words"), *[F.bit_or(F.when(lane == k, bit).otherwise(F.lit(0).cast("long"))).alias(f"bits{k}") for k in range(4)])


def _alike(pairs: DataFrame, percent: int) -> DataFrame:
    """pairs: a, b, x, y (two normalised lines). Gives a, b and ``ok``: whether the edits between the two are at most the rest of ``percent`` of the
    longer one. Written before it is filtered, as a filter would pull every step into one expression that computes each of them many times.

    Exchanging the words that differ place by place is one way to edit: if it is cheap enough, nothing else need be tried. Else the words that
    both lines begin and end with are set aside, which leaves the edit distance as it is. Of what is between, taking out
    the words that only one line has, and putting in those of the other, is another way where the rest is the same; else the distance is computed, first
    as if it were small."""
    size = lambda c: F.coalesce(F.length(c), F.lit(0))
    most = F.floor(F.greatest(F.length("x"), F.length("y")) * (100 - percent) / 100).cast("int")
    each = pairs.select("a", "b", F.split("x", " ").alias("v"), F.split("y", " ").alias("w"), most.alias("most"))
    swaps = F.aggregate(F.zip_with("v", "w", lambda c, d: F.when(c.eqNullSafe(d), 0).otherwise(1 + F.greatest(size(c), size(d)))), F.lit(0), lambda n, c: n + c)
    each = each.withColumn("swapped", swaps <= F.col("most"))

    def shared(c: Column, d: Column) -> Column:
        first = F.array_position(F.zip_with(c, d, lambda e, f: e.eqNullSafe(f)), False).cast("int")
        return F.coalesce(F.nullif(first, F.lit(0)) - 1, F.least(F.size(c), F.size(d)))

    each = each.withColumn("head", F.when(~F.col("swapped"), shared(F.col("v"), F.col("w"))))
    rest = lambda c: F.slice(c, F.col("head") + 1, F.size(c) - F.col("head"))
    each = each.withColumn("v", F.when(~F.col("swapped"), rest("v"))).withColumn("w", F.when(~F.col("swapped"), rest("w")))
    each = each.withColumn("tail", shared(F.reverse("v"), F.reverse("w")))
    each = each.select("a", "b", "most", "swapped", F.slice("v", 1, F.size("v") - F.col("tail")).alias("v"), F.slice("w", 1, F.size("w") - F.col("tail")).alias("w"))
    each = each.withColumn("less", F.array_except("v", "w")).withColumn("more", F.array_except("w", "v"))
    both = lambda c, out: F.array_join(F.filter(c, lambda x: ~F.array_contains(out, x)), " ")
    each = each.withColumn("v_both", both("v", F.col("less"))).withColumn("w_both", both("w", F.col("more")))
    each = each.select("a", "b", "most", "swapped", "v_both", "w_both", F.array_join("v", " ").alias("p"), F.array_join("w", " ").alias("q"))
    taken = (F.col("v_both") == F.col("w_both")) & (F.length("p") + F.length("q") - 2 * F.length("v_both") <= F.col("most"))
    # where one middle is empty, the other goes with one blank
    gap = (F.length("p") == 0) | (F.length("q") == 0)
    within = lambda most: F.call_function("levenshtein", F.col("p"), F.col("q"), most) >= 0
    ok = F.when(F.col("swapped"), True).when(gap, F.greatest(F.length("p"), F.length("q")) + 1 <= F.col("most"))
    ok = ok.when(taken, True).when(within(F.floor(F.col("most") / 8).cast("int")), True).otherwise(within(F.col("most")))
    return common.durable(each.select("a", "b", ok.alias("ok")), "tested")


def decide(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(doc_id, variant, gone): the numbers of the lines to remove, for texts that have any."""
    lines = common.durable(lines_of(docs), "lines", codec="zstd")
    nodes = common.durable(lines.groupBy("node").agg(F.min(_place()).alias("first"), F.max(_place()).alias("last")), "nodes")
    spots = common.durable(_shared(lines), "keys", tidy=True)
    texts = common.durable(_texts(lines, common.durable(spots.select("node").distinct(), "met")), "texts")
    marked = common.durable(_marked(texts), "marked")
    members = spots.join(common.small(marked, F.lit(64)), "node")

    def may(a, b) -> Column:
        near = 100 * F.least(a("length"), b("length")) >= percent * F.greatest(a("length"), b("length"))
        words = a("n_words") + b("n_words")
        unlike = sum(F.bit_count(a(f"bits{k}").bitwiseXOR(b(f"bits{k}"))) for k in range(4))
        return near & ((words < ASKED) | (100 * unlike <= UNLIKE * words))

    def test(pairs: DataFrame) -> DataFrame:
        both = pairs.join(texts.select(F.col("node").alias("a"), F.col("norm").alias("x")), "a").join(texts.select(F.col("node").alias("b"), F.col("norm").alias("y")), "b")
        return _alike(both, percent).where("ok").select("a", "b")

    roots, _ = grouping.link(members, test, may, native=True)
    tied = nodes.join(roots, "node", "left").where("root is not null or first < last").withColumn("root", F.coalesce("root", "node"))
    keep = tied.groupBy("root").agg(F.min("first").alias("keep"))
    groups = common.durable(tied.join(keep, "root").select("node", "keep"), "groups")
    gone = lines.select("node", "doc_id", "variant", "line_no").join(common.small(groups, F.lit(40)), "node").where(_place() != F.col("keep"))
    return gone.groupBy("doc_id", "variant").agg(F.array_sort(F.collect_set("line_no")).alias("gone"))


def within(x: str, y: str, most: int) -> bool:
    """Whether ``most`` edits turn x into y. What both begin and end with is set aside in whole words, which leaves the distance as it is; if
    exchanging the words that differ place by place is cheap enough, nothing else need be tried; else the distance is computed exactly, all rows
    of a column of its table at once as the bits of one integer."""
    v, w = x.split(" "), y.split(" ")
    least = min(len(v), len(w))
    head = next((i for i in range(least) if v[i] != w[i]), least)
    least -= head
    tail = next((i for i in range(least) if v[-1 - i] != w[-1 - i]), least)
    v, w = v[head : len(v) - tail], w[head : len(w) - tail]
    if len(v) == len(w) and sum(max(len(a), len(b)) for a, b in zip(v, w, strict=True) if a != b) <= most:
        return True
    p, q = " ".join(v), " ".join(w)
    if not v or not w:  # what is left goes with one blank
        return len(p) + len(q) + 1 <= most
    if abs(len(p) - len(q)) > most:
        return False
    at: dict[str, int] = {}
    for i, c in enumerate(p):
        at[c] = at.get(c, 0) | 1 << i
    every, last = (1 << len(p)) - 1, 1 << (len(p) - 1)
    up, down, score = every, 0, len(p)
    for left, c in zip(range(len(q) - 1, -1, -1), q, strict=True):
        same = at.get(c, 0) | down
        zero = (((same & up) + up) ^ up) | same
        plus, minus = down | ~(up | zero) & every, up & zero
        if plus & last:
            score += 1
        elif minus & last:
            score -= 1
        if score - left > most:
            return False
        plus, minus = plus << 1 | 1, minus << 1
        up, down = (minus | ~(zero | plus)) & every, plus & zero & every
    return score <= most


def with_removed(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(row, gone): the rows of ``docs`` as structs, and the numbers of the lines to remove (null: none)."""
    with common.scratch():
        found = common.durable(decide(docs, percent), "gone", keep=True)
    found = found.withColumnRenamed("doc_id", "of_doc").withColumnRenamed("variant", "of_variant")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("long").alias("doc_id"), _variant().alias("variant"))
    found = common.small(found, 32 + 4 * F.size("gone"))
    return rows.join(found, (F.col("doc_id") == F.col("of_doc")) & (F.col("variant") == F.col("of_variant")), "left").select("row", "gone")


def rest(text: Column, gone: Column) -> Column:
    """The text without the lines numbered in ``gone``."""
    return F.when(gone.isNull(), text).otherwise(F.array_join(F.filter(F.split(text, "\n"), lambda x, i: ~F.array_contains(gone, i)), "\n"))


def dedup(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """``docs`` with the repeated lines taken out of ``text`` and ``n_chars`` (where there is one) counted anew. A document all of whose
    lines repeat earlier ones holds nothing new and goes."""
    marked, gone, text = with_removed(docs, percent), F.col("gone"), F.col("row.text")
    kept = marked.where(gone.isNull() | (F.size(gone) < F.size(F.split(text, "\n")))).withColumn("text", rest(text, gone))
    new = {"text": F.col("text")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(gone.isNull(), F.col("row.n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType).alias("n_chars")
    return kept.select(*[new[c] if c in new else F.col(f"row.`{c}`") for c in docs.columns])
