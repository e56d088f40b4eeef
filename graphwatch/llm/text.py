"""Words, lines and keys of texts, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The characters that part words, as a set and as a pattern; a word.
WHITE = " \t\n\x0b\x0c\r"
WHITE_PATTERN = r"[\x20\x09-\x0D]+"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def text_or_empty(text: Column | str) -> Column:
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def strip(text: Column) -> Column:
    return F.btrim(text, F.lit(WHITE))


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def words(text: Column) -> Column:
    """Words of a text that is not null, in order; none of a blank text."""
    bare = strip(text)
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, WHITE_PATTERN))


def count_words(text: Column | str) -> Column:
    return F.regexp_count(text_or_empty(text), F.lit(WORD_PATTERN)).cast("long")


def once(value: Column) -> Column:
    """value, in a form that the optimizer does not copy into the places that use it (each of which would compute it again)."""
    return F.when(F.spark_partition_id() >= 0, value)
