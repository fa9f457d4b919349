"""Derived views of text: an invented marked script, canonical decomposition, and md5 buckets.

All are pure expressions. The marked script stands for a lower-resource language whose vowels are
combining signs: the same items, of the same difficulty, in another script.
"""

from __future__ import annotations

import unicodedata

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import StringType

#: The script table, one character to one, as hexadecimal code points.
SCRIPT = {
    "a": 0x093E, "b": 0x0915, "c": 0x0916, "d": 0x0917, "e": 0x0947, "f": 0x0918, "g": 0x0919, "h": 0x091A,
    "i": 0x093F, "j": 0x091B, "k": 0x091C, "l": 0x091D, "m": 0x091E, "n": 0x091F, "o": 0x094B, "p": 0x0920,
    "q": 0x0921, "r": 0x0922, "s": 0x0923, "t": 0x0924, "u": 0x0941, "v": 0x0925, "w": 0x0926, "x": 0x0927,
    "y": 0x0940, "z": 0x0928, "ß": 0x0929, "ä": 0x0948, "ç": 0x092A, "è": 0x0946,
    "é": 0x0945, "ê": 0x094E, "í": 0x0943, "ñ": 0x092B, "ó": 0x0949, "ö": 0x094A, "ü": 0x0942,
}
#: Letters of the given texts that have a canonical decomposition.
COMPOSED = "".join(map(chr, (0xC4, 0xC7, 0xC8, 0xC9, 0xCA, 0xCD, 0xD1, 0xD3, 0xD6, 0xDC, 0xE4, 0xE7, 0xE8, 0xE9, 0xEA, 0xED, 0xF1, 0xF3, 0xF6, 0xFC)))
LATIN, MARKED = "".join(SCRIPT), "".join(map(chr, SCRIPT.values()))


def abugida_view(text: Column) -> Column:
    """The text in the invented script; lengths in characters stay, mapped letters take three bytes."""
    return F.translate(F.lower(text), LATIN, MARKED)


def latin_view(text: Column) -> Column:
    """The way back (of lower-case text)."""
    return F.translate(text, MARKED, LATIN)


def decomposed_view(text: Column) -> Column:
    """Canonical decomposition of the letters that the given texts hold, without a UDF."""
    for c in COMPOSED:
        text = F.replace(text, F.lit(c), F.lit(unicodedata.normalize("NFD", c)))
    return text


def composed_view(text: Column) -> Column:
    """The inverse of ``decomposed_view``."""
    for c in COMPOSED:
        text = F.replace(text, F.lit(unicodedata.normalize("NFD", c)), F.lit(c))
    return text


@pandas_udf(StringType())
def normalize_nfc(text):
    """Canonical composition of any text (the general case, in Arrow batches)."""
    return text.map(lambda x: None if x is None else unicodedata.normalize("NFC", x))


def bucket(tag: str, *parts: Column) -> Column:
    """A number in [0, 2^32) that follows from the tag and the parts alone, alike in any engine with md5."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(tag), *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("long")


def sql_bucket(tag: str, *parts: str) -> str:
    """The same for DuckDB."""
    return f"('0x' || substr(md5(concat_ws('|', '{tag}', {', '.join(parts)})), 1, 8))::bigint"


def sql_abugida(text: str) -> str:
    return f"translate(lower({text}), '{LATIN}', '{MARKED}')"


def sql_decomposed(text: str) -> str:
    for c in COMPOSED:
        text = f"replace({text}, '{c}', '{unicodedata.normalize('NFD', c)}')"
    return text
