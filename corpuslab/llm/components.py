"""Connected components of a link table, by rounds of least-neighbour pointers; nothing but counts reaches the driver.

Every node points to the least of itself and its neighbours, which gives trees; pointers are doubled until all point to
roots; links between different roots are what the next round works on. Sums over a node's links are taken inside tasks first, and
look-ups are salted, so that a node with a third of all links burdens no single task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ensure_checkpoint_dir

#: Parts that the rows of one key are dealt to in a look-up.
SALTS = 16


def look_up(rows: DataFrame, key: str, table: DataFrame, name: str) -> DataFrame:
    """``rows`` with ``name``: what ``table(node, root)`` says of the key's node, else the key itself."""
    wide = table.select(F.col("node").alias("_node"), F.col("root").alias("_root"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("_part"))
    dealt = rows.withColumn("_salt", F.pmod(F.xxhash64(*rows.columns), F.lit(SALTS)).cast("int"))
    met = dealt.join(wide, (F.col(key) == F.col("_node")) & (F.col("_salt") == F.col("_part")), "left")
    return met.select(*rows.columns, F.coalesce("_root", key).alias(name))


def roots_of(pointers: DataFrame, max_rounds: int = 64) -> DataFrame:
    """``node`` and ``root``: pointers ``root`` <= ``node`` followed to their ends, twice as far in each round."""
    state = pointers
    for _ in range(max_rounds):
        asked = state.select(F.col("root").alias("node")).distinct()
        moving = state.where("node <> root").join(asked, "node", "left_semi").checkpoint()
        if not moving.limit(1).count():
            return state
        state = look_up(state, "root", moving, "up").select("node", F.col("up").alias("root")).checkpoint()
    raise RuntimeError("pointers did not settle")


def least_neighbours(links: DataFrame) -> DataFrame:
    """``node`` and ``root``, the least of it and its neighbours, for every node of ``links(a, b)``."""
    both = links.select(F.inline(F.array(F.struct(F.col("a").alias("node"), F.col("b").alias("other")), F.struct(F.col("b").alias("node"), F.col("a").alias("other")))))
    return both.groupBy("node").agg(F.min("other").alias("_least")).select("node", F.least("node", "_least").alias("root"))


def components(links: DataFrame, max_rounds: int = 64) -> DataFrame:
    """``node`` and ``root`` (the least node reachable) for every node of ``links(a, b)``, both longs and not null.

    Repeated links and links of a node to itself do no harm. Each round at least halves the number of trees and is checkpointed to the
    shared folder, so that lost executors cost no recomputed rounds. An empty table gives an empty one.
    """
    ensure_checkpoint_dir(links.sparkSession)
    labels = None
    for _ in range(max_rounds):
        found = roots_of(least_neighbours(links).checkpoint())
        labels = found if labels is None else look_up(labels, "root", found, "up").select("node", F.col("up").alias("root")).checkpoint()
        links = look_up(look_up(links, "a", found, "_a"), "b", found, "_b").where("_a <> _b")
        links = links.select(F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b")).distinct().checkpoint()
        if not links.limit(1).count():
            return labels
    raise RuntimeError("components did not settle")
