"""What counts as a word: a maximal run of characters other than the six ASCII white-space characters."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Space, tab, line feed, vertical tab, form feed, carriage return.
WHITE = " \t\n\x0b\x0c\r"
WHITE_RUN = "[\\x20\\x09-\\x0D]+"


def words_of(text: Column) -> Column:
    """Array of the words of a text; null and blank texts give an empty array."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), WHITE_RUN), "")


def trimmed(text: Column) -> Column:
    return F.btrim(text, F.lit(WHITE))
