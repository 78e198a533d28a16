"""Words of a text, as SQL expressions that stay in the JVM.

Lower-casing A-Z alone is slow over whole texts (translate looks up every character), so
there are three ways: `words` is exact on any text; `words_as_written` leaves the case,
and `lower_word` is then put on single words; `words_for_ascii` lowers all letters, which
gives the same result for whoever looks for words of ASCII characters only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import lower_ascii

#: ASCII signs and white space; every other character belongs to a word (capitals as well, before they are lowered).
SIGNS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: The one letter outside ASCII whose small letter is in ASCII.
KELVIN = "K"


def words(text: Column) -> Column:
    """Array of the words, A-Z lower-cased; of a null text none."""
    return without_ends(F.split(lower_ascii(F.coalesce(text, F.lit(""))), SIGNS))


def words_as_written(text: Column) -> Column:
    """Array of the words in their case."""
    return without_ends(F.split(F.coalesce(text, F.lit("")), SIGNS))


def plain_lower(text: Column) -> Column:
    """For words_for_ascii."""
    return F.lower(F.replace(F.coalesce(text, F.lit("")), F.lit(KELVIN), F.lit("\ufffd")))


def words_for_ascii(text: Column) -> Column:
    """Array of the words; those of ASCII characters as words() has them, and no others are in ASCII."""
    return without_ends(F.split(plain_lower(text), SIGNS))


def with_words(df: DataFrame, keep: list[str], text: Column, into: str = "w") -> DataFrame:
    """df's columns `keep`, and the words of a (lowered) text: in steps, so that it is split once, which one expression doesn't ensure inside a generator or filter."""
    return df.select(*keep, F.split(text, SIGNS).alias("split_text")).select(*keep, without_ends(F.col("split_text")).alias(into))


def lower_word(word: Column) -> Column:
    """A-Z to a-z in one word."""
    return F.when(F.octet_length(word) == F.char_length(word), F.lower(word)).otherwise(lower_ascii(word))


def without_ends(parts: Column) -> Column:
    """Drops the empty strings that split() leaves before a leading and after a trailing sign."""
    head = F.when(F.element_at(parts, 1) == "", 1).otherwise(0)
    tail = F.when(F.element_at(parts, -1) == "", 1).otherwise(0)
    return F.slice(parts, 1 + head, F.greatest(F.size(parts) - head - tail, F.lit(0)))
