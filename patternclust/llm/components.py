"""Connected components of an undirected graph held in a DataFrame of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import drop, materialize


def connected_components(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """``(node, root)`` for every node of a link; ``root`` is the smallest node that it reaches.

    Alternates the two star operations: each round hangs the larger neighbours of a node, then
    the smaller ones, under the smallest of them, until the set of links stands still. All
    minima are aggregates with map-side combine and all look-ups are equi-joins of exchanges,
    so a hub never gathers in one task. Links to oneself, repeated links and nulls are ignored;
    an empty input gives an empty result.
    """
    x, y = F.col(a), F.col(b)
    stars = materialize(
        links.where(x != y).select(F.greatest(x, y).alias("hi"), F.least(x, y).alias("lo")).distinct(), "links"
    )
    before = _signature(stars)
    for _ in range(max_rounds):
        if before[0] == 0:
            break
        both = stars.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(
            stars.select(F.col("lo").alias("u"), F.col("hi").alias("v"))
        )
        least = materialize(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "least")
        large = materialize(
            stars.join(least, stars["lo"] == least["u"]).select("hi", F.col("m").alias("lo")).distinct(), "large"
        )
        under = materialize(large.groupBy(F.col("hi").alias("u")).agg(F.min("lo").alias("m")), "under")
        moved = large.join(under, large["hi"] == under["u"]).where(F.col("lo") != F.col("m"))
        after = materialize(
            moved.select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
            .unionByName(under.select(F.col("u").alias("hi"), F.col("m").alias("lo")))
            .distinct(),
            "stars",
        )
        now = _signature(after)
        for old in (stars, least, large, under):
            drop(old)
        stars = after
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    pairs = stars.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
    return pairs.unionByName(stars.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct())


def _signature(links: DataFrame) -> tuple:
    row = links.agg(
        F.count(F.lit(1)).alias("n"),
        F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)")).alias("s"),
    ).first()
    return row["n"], row["s"]
