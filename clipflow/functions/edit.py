"""Edit distances as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Printable ASCII without quote and backslash: a character for each distinct word of a pair.
WORD_CODES = "".join(chr(i) for i in range(33, 127) if chr(i) not in "'\\") + "".join(chr(i) for i in range(256, 4096))


def encode_words(ref: str, hyp: str, words: str) -> Column:
    """The array as a string, one character for each distinct word of the pair. Pairs have at most 3,900 distinct words."""
    return F.expr(f"transform(array(array_sort(array_union({ref}, {hyp}))), d -> array_join(transform({words}, w -> substring('{WORD_CODES[:92]}' || '{WORD_CODES[92:]}', cast(array_position(d, w) AS int), 1)), ''))[0]")


def edit_words(ref: str, hyp: str) -> Column:
    return F.levenshtein(encode_words(ref, hyp, ref), encode_words(ref, hyp, hyp)).cast("long")


def edit_text(ref: Column, hyp: Column) -> Column:
    return F.levenshtein(ref, hyp).cast("long")
