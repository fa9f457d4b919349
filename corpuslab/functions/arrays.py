"""Array helpers whose cost is linear in the array."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def grams(items: Column, n: int, glue: str = " ") -> Column:
    """All runs of ``n`` neighbours, joined; none where there are fewer. Shifted slices are zipped: the array is built n times, not once for each run."""
    count = F.greatest(F.size(items) - (n - 1), F.lit(0))
    out = F.slice(items, F.lit(1), count)
    for j in range(1, n):
        out = F.zip_with(out, F.slice(items, F.lit(j + 1), count), lambda a, b: F.concat_ws(glue, a, b))
    return out


def once(df: DataFrame, *keep: str, **columns: Column) -> DataFrame:
    """``keep`` and computed ``columns``, each computed once a row: the step between stops the optimizer from writing a costly expression out at each of its later uses."""
    held = F.explode(F.array(F.struct(*[c.alias(k) for k, c in columns.items()]))).alias("_once")
    return df.select(*keep, held).select(*keep, *[F.col(f"_once.{k}").alias(k) for k in columns])


def hashed_grams(items: Column, n: int) -> Column:
    """A 64-bit number for each run of ``n`` neighbours, in their order; no run is built as text. Equal numbers are candidates, not yet equal runs. ``items`` should be a column that ``once`` made."""
    count = F.greatest(F.size(items) - (n - 1), F.lit(0))
    return F.transform(F.slice(items, F.lit(1), count), lambda x, i: F.xxhash64(x, *[F.get(items, i + j) for j in range(1, n)]))
