"""Column expressions shared by the text operators (JVM side only)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: ASCII white space: space, and tab to carriage return.
BLANKS = " \t\n\x0b\x0c\r"
#: Stands for a null document id in joins.
NO_ID = -(2**63)


def ascii_lower(c: Column) -> Column:
    """Lower-cases A-Z only. Pure ASCII strings take the fast built-in way."""
    return F.when(F.octet_length(c) == F.char_length(c), F.lower(c)).otherwise(F.translate(c, UPPER, LOWER))


def ascii_strip(c: Column) -> Column:
    """Strips ASCII white space at both ends; the trim runs only where an end has some."""
    edge = (F.substring(c, 1, 1) <= " ") | (F.substring(c, -1, 1) <= " ")
    return F.when(edge, F.btrim(c, F.lit(BLANKS))).otherwise(c)


def text_lines(text: Column) -> Column:
    """All lines of a text; null and empty give one empty line."""
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def id_key(doc_id: Column) -> Column:
    return F.coalesce(doc_id.cast("long"), F.lit(NO_ID))


def free_names(df: DataFrame, *wanted: str) -> list[str]:
    """Names like ``wanted`` that no column of ``df`` has (names are compared without case)."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in wanted:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def words_of(text: Column) -> Column:
    """Words ``[^\\x20\\x09-\\x0D]+`` of the text with A-Z lower-cased, as an array."""
    return F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), "[ \\x09-\\x0D]+", -1), lambda w: w != "")


#: Rows of narrow id tables that may be broadcast (about 24 bytes each); a larger one is shuffled.
BROADCAST_ROWS = 500_000


def sized(ids: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """``ids`` with a broadcast hint if it has at most ``most`` rows, else to be joined by a shuffle."""
    return F.broadcast(ids) if ids.limit(most + 1).count() <= most else ids.hint("merge")
