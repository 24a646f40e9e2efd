"""Connected components by alternating large-star and small-star steps over a table of links.

Every step is a grouped minimum (combined before its shuffle) joined back to the links, written to
the shared folder; nothing but two numbers per round reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import discard, observed


def _directed(links: DataFrame) -> DataFrame:
    return links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _large_star(links: DataFrame) -> DataFrame:
    both = _directed(links)
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u").where("v > u AND v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(links: DataFrame) -> DataFrame:
    down = links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, component): for every node of links (u, v) the smallest node reachable. Raises if it has
    not settled after `rounds`; the number needed grows with the logarithm of the longest path."""
    measures = {"n": F.count(F.lit(1)), "h": F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))}
    once = links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct()
    now, mark = observed(once, "links", **measures)
    for _ in range(rounds if mark["n"] else 0):
        new, told = observed(_small_star(_large_star(now)), "links", **measures)
        discard(now)
        now = new
        if told == mark:
            break
        mark = told
    else:
        if mark["n"]:
            raise RuntimeError(f"components did not settle in {rounds} rounds")
    out = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    out._scratch_path, out.links = now._scratch_path, mark["n"]
    return out
