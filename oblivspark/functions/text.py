"""Text expressions that match byte-exact contracts."""

from __future__ import annotations

import string

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed value: the pattern of a white-space separated word.
WORD = r"[^\x20\x09-\x0D]+"


def ascii_lower(text: Column) -> Column:
    """Lower-case A to Z and nothing else; the quick built-in serves texts without wider characters."""
    narrow = F.octet_length(text) == F.length(text)
    return F.when(narrow, F.lower(text)).otherwise(
        F.translate(text, string.ascii_uppercase, string.ascii_lowercase)
    )


def word_count(text: Column) -> Column:
    """Number of white-space separated words; null counts as the empty text."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")
