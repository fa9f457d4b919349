"""Pre-token rules, and how they cut words of scripts with combining marks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = r"\S+"
CHUNK = r" ?\S+|\s+(?!\S)|\s+"
#: Word classes: letters alone cut a word at every combining mark; letters with marks don't.
CLASSES = {"letters": r"\p{L}", "letters_marks": r"\p{L}\p{M}"}


@dataclass(frozen=True)
class PretokenRule:
    """A published family of patterns, part by part; the default options are those of byte-level tokenizers."""

    word: str = "letters_marks"
    leading_space: bool = True
    contractions: bool = True
    digits: str = "+"
    trailing_space: bool = True

    def pattern(self) -> str:
        w, space = CLASSES[self.word], " ?" if self.leading_space else ""
        parts = [r"'(?:s|t|re|ve|m|ll|d)"] if self.contractions else []
        parts += [rf"{space}[{w}]+", rf"{space}\p{{N}}{self.digits}", rf"{space}[^\s\p{{N}}{w}]+"]
        return "|".join(parts + ([r"\s+(?!\S)"] if self.trailing_space else []) + [r"\s+"])


def pretokenize(text: Column, rule: str | PretokenRule = "letters_marks") -> Column:
    """Pieces of a text: by a word class, or white-space words, characters, or bytes (as hexadecimal pairs)."""
    if rule == "space":
        return F.regexp_extract_all(text, F.lit(WORD), F.lit(0))
    if rule == "char":
        return F.filter(F.split(text, ""), lambda x: x != "")
    if rule == "byte":
        return F.regexp_extract_all(F.hex(F.encode(text, "UTF-8")), F.lit(".."), F.lit(0))
    rule = PretokenRule(rule) if isinstance(rule, str) else rule
    return F.regexp_extract_all(text, F.lit(rule.pattern()), F.lit(0))


def n_words(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def n_pieces(text: Column, rule: str) -> Column:
    """Word pieces alone (no white space, digits or marks of punctuation)."""
    return F.regexp_count(text, F.lit(f"[{CLASSES[rule]}]+")).cast("long")


def fragmentation(df: DataFrame, by: list[str], rule: str, text: str = "text") -> DataFrame:
    """Words, pieces and pieces for each word by group; one shuffle of partial sums."""
    sums = df.groupBy(*by).agg(F.sum(n_words(F.col(text))).alias("words"), F.sum(n_pieces(F.col(text), rule)).alias("pieces"))
    return sums.withColumn("ratio", F.round(F.col("pieces") / F.col("words"), 6))


def fertility_floor(df: DataFrame, by: list[str], rule: str, text: str = "text") -> DataFrame:
    """Pieces that aren't white space for each word: no vocabulary and no data gets below, as merges never cross a piece."""
    visible = F.size(F.filter(pretokenize(F.col(text), rule), lambda p: ~p.rlike(r"^\s+$"))).cast("long")
    sums = df.groupBy(*by).agg(F.sum(n_words(F.col(text))).alias("words"), F.sum(visible).alias("pieces"))
    return sums.withColumn("floor", F.round(F.col("pieces") / F.col("words"), 6))


def rule_difference(df: DataFrame, text: str = "text") -> DataFrame:
    """Documents that the two word classes cut differently."""
    return df.where(pretokenize(F.col(text), "letters") != pretokenize(F.col(text), "letters_marks"))


def piece_histogram(df: DataFrame, rule: str | PretokenRule, by: list[str] | None = None, text: str = "text", count: str | None = None) -> DataFrame:
    """``piece`` and ``cnt`` by group; pieces are counted inside tasks before the one shuffle. ``count`` names a column with the number of times that each text stands."""
    pieces = df.select(*(by or []), *([count] if count else []), F.explode(pretokenize(F.col(text), rule)).alias("piece"))
    return pieces.groupBy(*(by or []), "piece").agg((F.sum(count) if count else F.count(F.lit(1))).alias("cnt"))


def chunk_histogram(df: DataFrame, by: list[str] | None = None, text: str = "text") -> DataFrame:
    """``chunk`` and ``cnt`` by group: white space as the named rules cut it, and words with a space before them.

    No piece of these rules crosses a chunk, and each chunk is cut alone as it is in its text, so one scan serves both rules and the number of words.
    """
    chunks = df.select(*(by or []), F.explode(F.regexp_extract_all(F.col(text), F.lit(CHUNK), F.lit(0))).alias("chunk"))
    return chunks.groupBy(*(by or []), "chunk").agg(F.count(F.lit(1)).alias("cnt"))
