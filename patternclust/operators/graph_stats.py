"""Counts over compact graphs: statistics, frequent parts, quantiles, sample levels, features."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import triples, with_size


def describe(graphs: DataFrame) -> DataFrame:
    """One row of counts; labels are counted as distinct values, so nothing gathers but partial counts."""
    n_v, n_e = F.size("vl"), F.size("eu")
    counts = graphs.agg(
        F.count(F.lit(1)).alias("n_graphs"), F.min(n_v).cast("bigint").alias("v_min"), F.max(n_v).cast("bigint").alias("v_max"), F.round(F.avg(n_v), 6).alias("v_avg"),
        F.min(n_e).cast("bigint").alias("e_min"), F.max(n_e).cast("bigint").alias("e_max"), F.round(F.avg(n_e), 6).alias("e_avg"),
    )
    kinds = lambda kind, column: F.transform(F.array_distinct(column), lambda x: F.struct(F.lit(kind).alias("kind"), x.alias("l")))
    labels = graphs.select(F.explode(F.concat(kinds("v", "vl"), kinds("e", "el"))).alias("x")).distinct()
    n_of = lambda kind: F.count(F.when(F.col("x.kind") == kind, 1))
    return counts.crossJoin(F.broadcast(labels.agg(n_of("v").alias("n_vlabels"), n_of("e").alias("n_elabels"))))  # one row each


def frequent_vertices(graphs: DataFrame, minsup: float) -> DataFrame:
    """``(l, n_support, supp)`` of labels in at least ``minsup`` of the graphs."""
    return _frequent(graphs, graphs.select(F.explode(F.array_distinct("vl")).alias("l")), ["l"], minsup)


def frequent_paths(graphs: DataFrame, minsup: float) -> DataFrame:
    """``(la, le, lb, n_support, supp)`` of length-1 paths, distinct within a graph without an exchange."""
    ends = F.transform(F.arrays_zip("eu", "ew", "el"), lambda e: F.struct(F.element_at("vl", e["eu"] + 1).alias("x"), e["el"].alias("le"), F.element_at("vl", e["ew"] + 1).alias("y")))
    keys = F.array_distinct(F.transform(ends, lambda e: F.struct(F.least(e["x"], e["y"]).alias("la"), e["le"].alias("le"), F.greatest(e["x"], e["y"]).alias("lb"))))
    return _frequent(graphs, graphs.select(F.explode(keys).alias("k")).select("k.*"), ["la", "le", "lb"], minsup)


def _frequent(graphs: DataFrame, rows: DataFrame, keys: list[str], minsup: float) -> DataFrame:
    total = graphs.agg(F.count(F.lit(1)).alias("total"))
    counted = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_support")).crossJoin(F.broadcast(total))
    return counted.withColumn("supp", F.col("n_support") / F.col("total")).where(F.col("supp") >= minsup).select(*keys, "n_support", F.round("supp", 6).alias("supp"))


def vmax_quantile(graphs: DataFrame, minsups) -> DataFrame:
    """``(minsup, vmax)``: the discrete (1 - minsup) quantile of vertex counts."""
    spark = graphs.sparkSession
    sizes = graphs.groupBy(F.size("vl").alias("n_v")).count()  # few rows, whatever the number of graphs
    w = Window.orderBy("n_v")
    upto = sizes.withColumn("upto", F.sum("count").over(w)).withColumn("total", F.sum("count").over(Window.partitionBy(F.lit(1))))
    asked = spark.createDataFrame([(float(m),) for m in minsups], "minsup double")
    reach = F.col("upto") >= F.greatest(F.ceil(F.round((1 - F.col("minsup")) * F.col("total"), 6)), F.lit(1))
    return asked.join(upto, reach).groupBy("minsup").agg(F.min("n_v").cast("bigint").alias("vmax"))


def doublings(n: int, h_min: int = 30) -> int:
    level = 0
    while h_min << level < n:
        level += 1
    return level


def sample_levels(graphs: DataFrame, hit, seed: str = "7", h_min: int = 30) -> DataFrame:
    """``(level, n, k_hits)`` of nested samples of 30, 60, ... graphs in hash order, while smaller than all.

    Ranks are only needed for the samples; the scan keeps what can be in the largest by its hash.
    """
    order = F.md5(F.concat(F.col("graph_id").cast("string"), F.lit(f":{seed}")))
    rows = graphs.select(order.alias("h"), hit.cast("int").alias("hit"))
    n = graphs.count()
    spark = graphs.sparkSession
    # buckets of the hash give running counts without one sorted partition of all rows
    bucketed = rows.withColumn("b", F.substring("h", 1, 3))
    sums = bucketed.groupBy("b").agg(F.count(F.lit(1)).alias("c")).withColumn("before", F.coalesce(F.sum("c").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    ranked = bucketed.join(sums.select("b", "before"), "b").withColumn("rank", F.col("before") + F.row_number().over(Window.partitionBy("b").orderBy("h")))
    levels = spark.createDataFrame([(j, h_min << j) for j in range(doublings(n, h_min))], "level int, n bigint")
    first = ranked.groupBy(F.ceil(F.greatest(F.lit(0.0), F.log2(F.col("rank") / h_min))).cast("int").alias("at")).agg(F.sum("hit").alias("hits"))
    return levels.join(first, F.col("at") <= F.col("level"), "left").groupBy("level", "n").agg(F.coalesce(F.sum("hits"), F.lit(0)).cast("bigint").alias("k_hits"))


def three_vertex_features(graphs: DataFrame) -> DataFrame:
    """``(graph_id, feature, cnt)``: labelled connected subgraphs on three vertices, paths and triangles, within the row."""
    near = F.arrays_zip("eu", "ew", "el")
    both = F.flatten(F.transform(near, lambda e: F.array(F.struct(e["eu"].alias("m"), e["ew"].alias("o"), e["el"].alias("l")), F.struct(e["ew"].alias("m"), e["eu"].alias("o"), e["el"].alias("l")))))
    wide = graphs.select("graph_id", "vl", "eu", "ew", "el", both.alias("arcs"))
    arm = wide.select("graph_id", "vl", "eu", "ew", "el", "arcs", F.explode("arcs").alias("p"))
    pair = arm.select("graph_id", "vl", "eu", "ew", "el", "p", F.explode(F.filter("arcs", lambda q: (q["m"] == F.col("p.m")) & (q["o"] > F.col("p.o")))).alias("q"))
    label = lambda i: F.element_at("vl", i + 1)
    closed = F.try_element_at(F.filter(F.arrays_zip("eu", "ew", "el"), lambda e: (e["eu"] == F.col("p.o")) & (e["ew"] == F.col("q.o"))), F.lit(1))
    side = lambda o, line: F.concat_ws(":", line, label(o))
    path = F.concat_ws("/", F.lit("P"), label(F.col("p.m")), F.least(side(F.col("p.o"), F.col("p.l")), side(F.col("q.o"), F.col("q.l"))), F.greatest(side(F.col("p.o"), F.col("p.l")), side(F.col("q.o"), F.col("q.l"))))
    # a triangle is met at each of its vertices: its key is the sorted list of (vertex, facing edge); counted at the smallest
    corner = lambda v, facing: F.concat_ws(":", v, facing)
    ring = F.concat_ws("/", F.lit("T"), F.array_sort(F.array(corner(label(F.col("p.m")), closed["el"]), corner(label(F.col("p.o")), F.col("q.l")), corner(label(F.col("q.o")), F.col("p.l")))))
    feature = F.when(closed.isNull(), path).when(F.col("p.m") < F.col("p.o"), ring)
    return pair.select("graph_id", feature.alias("feature")).where("feature IS NOT NULL").groupBy("graph_id", "feature").agg(F.count(F.lit(1)).alias("cnt"))


def wl_features(graphs: DataFrame, rounds: int = 1) -> DataFrame:
    """``(graph_id, wl, cnt)``: labels after some rounds of hashing each with its sorted neighbours."""
    held = graphs.select("graph_id", "vl", "eu", "ew", "el")
    for _ in range(rounds):
        held = held.withColumn("vl", _relabelled())
    return held.select("graph_id", F.explode("vl").alias("wl")).groupBy("graph_id", "wl").agg(F.count(F.lit(1)).alias("cnt"))


def wl_histogram(graphs: DataFrame) -> DataFrame:
    """``(wl, n)`` over all graphs after one round, counted at once."""
    return graphs.select(F.explode(_relabelled()).alias("wl")).groupBy("wl").agg(F.count(F.lit(1)).alias("n"))


def _relabelled():
    """New labels within the row: neighbours are gathered per vertex as sorted (vertex, text) pairs, then hashed."""
    label = lambda i: F.element_at("vl", i + 1)
    edges = F.arrays_zip("eu", "ew", "el")
    arcs = F.flatten(F.transform(edges, lambda e: F.array(F.struct(e["eu"].alias("m"), F.concat_ws(":", e["el"], label(e["ew"])).alias("t")), F.struct(e["ew"].alias("m"), F.concat_ws(":", e["el"], label(e["eu"])).alias("t")))))
    arcs = F.array_sort(arcs)
    return F.transform("vl", lambda x, i: F.md5(F.concat_ws("|", x, F.concat_ws(",", F.transform(F.filter(arcs, lambda a: a["m"] == i), lambda a: a["t"])))))


def walk_features(graphs: DataFrame) -> DataFrame:
    """``(walk, n)``: label sequences of walks with two edges, vertices may come again; both directions count."""
    arcs = F.flatten(F.transform(F.arrays_zip("eu", "ew", "el"), lambda e: F.array(F.struct(e["eu"].alias("m"), e["ew"].alias("o"), e["el"].alias("l")), F.struct(e["ew"].alias("m"), e["eu"].alias("o"), e["el"].alias("l")))))
    first = graphs.select("vl", arcs.alias("arcs")).select("vl", "arcs", F.explode("arcs").alias("p"))
    second = first.select("vl", "p", F.explode(F.filter("arcs", lambda q: q["m"] == F.col("p.o"))).alias("q"))
    label = lambda i: F.element_at("vl", i + 1)
    walk = F.concat_ws("/", label(F.col("p.m")), F.col("p.l"), label(F.col("p.o")), F.col("q.l"), label(F.col("q.o")))
    return second.select(walk.alias("walk")).groupBy("walk").agg(F.count(F.lit(1)).alias("n"))


def sizes(graphs: DataFrame) -> DataFrame:
    return with_size(graphs).select(F.col("graph_id").alias("g"), F.size("vl").cast("bigint").alias("n_v"), F.size("eu").cast("bigint").alias("n_e"), F.col("gsize").cast("bigint").alias("gsize"))


__all__ = ["describe", "frequent_vertices", "frequent_paths", "vmax_quantile", "doublings", "sample_levels", "three_vertex_features", "wl_features", "walk_features", "sizes", "triples"]
