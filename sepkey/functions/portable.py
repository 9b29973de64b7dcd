"""Randomness that is equal in every SQL engine: MD5 of integer-only text.

A rank is the MD5 of ``seed|identity``; a draw is the first 15 hex digits of an MD5, a number below 2^60 whose remainder by n is uniform up to n / 2^60.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

DIGITS = 15
SPAN = 16**DIGITS


def part_text(c: Column) -> Column:
    """A value's text with bars and backslashes escaped and nulls named, so that lists of parts read back in one way only. Numbers stay as they are."""
    text = F.replace(F.replace(c.cast("string"), F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|"))
    return F.coalesce(text, F.lit("\\N"))


def rank_text(seed: int, identity: list[Column]) -> Column:
    return F.concat_ws("|", F.lit(str(seed)), *map(part_text, identity))


def rank(seed: int, identity: list[Column]) -> Column:
    return F.md5(rank_text(seed, identity))


def number(text: Column) -> Column:
    """The first 15 hex digits of the MD5 of a text, as a BIGINT."""
    return F.conv(F.substring(F.md5(text), 1, DIGITS), 16, 10).cast("long")


def draw(seed: int, slot: Column, name: str | Column) -> Column:
    return number(F.concat_ws("|", F.lit(str(seed)), slot.cast("string"), F.lit(name)))


# The same in SQL text for other engines.


def sql_rank(seed: int, identity: list[str]) -> str:
    return "md5(concat_ws('|', '" + str(seed) + "', " + ", ".join(f"CAST({c} AS VARCHAR)" for c in identity) + "))"


def sql_number(text: str) -> str:
    return f"CAST(concat('0x', substr(md5({text}), 1, {DIGITS})) AS BIGINT)"


def sql_draw(seed: int, slot: str, name: str) -> str:
    return sql_number(f"concat_ws('|', '{seed}', CAST({slot} AS VARCHAR), '{name}')")
