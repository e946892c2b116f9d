"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

All of it is DataFrame expressions. Every document draws an exponential key, scaled by its
quality weight; within a source the keys are sorted and sizes summed up to the budget that
complete epochs leave. The sum runs over key buckets first (a source is spread over many
buckets), then within a bucket, so a source with a third of all rows is no single task's work.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .store import materialize

WORD = r"[^\x20\x09-\x0D]+"
#: marks that lower a document's quality weight
NOISE_MARKS = "!|*#%&$"
SOURCE_WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3


def quality_weight(text):
    """Weight in [0.05, 1]: one less four times the share of noise marks among the characters."""
    whole = F.length(F.coalesce(text, F.lit("")))
    marks = whole - F.length(F.translate(F.coalesce(text, F.lit("")), NOISE_MARKS, ""))
    return F.greatest(F.lit(0.05), F.lit(1.0) - F.lit(4.0) * marks / F.greatest(whole, F.lit(1)))


def source_targets(sizes: DataFrame, weights=SOURCE_WEIGHTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """``(source, source_size, target)`` from ``(source, source_size)``, one row per source.

    Sources by code point, null last, take the weights in turn. Targets share the total by
    weight; none exceeds ``max_epochs`` times its size, the excess going to the others by weight.
    """
    turn = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn % len(weights) + 1).cast("int"))
    ranked = sizes.withColumn("w", weight).withColumn("cap", F.col("source_size").cast("double") * max_epochs)
    ranked = ranked.withColumn("r", F.col("cap") / F.col("w"))
    by_ratio = Window.orderBy("r", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    everywhere = Window.partitionBy(F.lit(1))
    filled = ranked.withColumn("full", F.sum("cap").over(by_ratio) - F.col("cap")).withColumn(
        "open", F.sum("w").over(everywhere) - F.sum("w").over(by_ratio) + F.col("w")
    )
    filled = filled.withColumn("level", (F.sum(F.col("source_size").cast("double")).over(everywhere) - F.col("full")) / F.col("open"))
    level = F.min(F.when(F.col("level") <= F.col("r"), F.struct("r", "level"))).over(everywhere)["level"]
    return filled.withColumn("at", level).select("source", "source_size", F.least("cap", F.col("at") * F.col("w")).alias("target"))


def mixture(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
    weights=SOURCE_WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: str = "mix",
) -> DataFrame:
    """One row per row of ``docs``: ``doc_id, source, text_hash, size, source_size, target, copies, taken``.

    Null or blank text: size 0, taken 0. A null source is a source of its own, the last. Rows that
    repeat id and text tie, and which of them is taken is then all one. A source of size 0 has target 0; an
    empty table gives an empty result. Other columns are ignored. Draws depend on id, text and seed only, so
    reruns agree; null ids draw apart by their texts.
    """
    text = F.col(text_col)
    name = F.concat_ws(":", F.coalesce(F.col(id_col).cast("string"), F.lit("null")), F.md5(F.coalesce(text, F.lit(""))))
    draw = (F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), name)), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)
    sized = materialize(
        docs.select(
            F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.xxhash64(text).alias("text_hash"),
            F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("bigint").alias("size"),
            (-F.ln(draw) / quality_weight(text)).alias("key"),
        ),
        "sized",
    )
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n"))
    totals = materialize(totals, "totals")
    n = totals.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    per_octave = min(1 << 13, max(256, n // 10_000))  # buckets of even ratio: a thousandth of a source's rows at most
    plan = source_targets(totals.select("source", "source_size"), weights, max_epochs)
    epochs = F.when(F.col("source_size") > 0, F.floor((F.col("target") + 1e-6) / F.col("source_size"))).otherwise(F.lit(0))
    plan = materialize(
        plan.withColumn("epochs", epochs.cast("bigint")).withColumn("budget", F.col("target") - F.col("epochs") * F.col("source_size")),
        "plan",
    )
    keyed = sized.withColumn("src", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n"))).withColumn(
        "bucket", F.floor(F.log2("key") * per_octave).cast("int")
    )
    sums = keyed.groupBy("src", "bucket").agg(F.sum("size").alias("in_bucket"))
    before = Window.partitionBy("src").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base", F.coalesce(F.sum("in_bucket").over(before), F.lit(0))).drop("in_bucket")
    named = plan.withColumn("src", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n"))).drop("source")
    starts = materialize(sums.join(named, "src"), "starts")
    within = Window.partitionBy("src", "bucket").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    summed = keyed.join(starts, ["src", "bucket"]).withColumn("upto", F.col("base") + F.sum("size").over(within))
    under = F.col("budget") - (F.col("upto") - F.col("size"))
    extra = (F.col("upto") <= F.col("budget")) | ((under > 0) & (F.col("upto") - F.col("budget") < under))
    copies = F.col("epochs") + F.when(extra & (F.col("epochs") < max_epochs) & (F.col("size") > 0), 1).otherwise(0)
    return summed.withColumn("copies", copies).select(
        "doc_id", "source", "text_hash", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken")
    )


def mix_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """``docs`` with each row repeated as often as the mix takes it (not at all: left out).

    Of rows that repeat id, text and source, as many are repeated as often as planned, the first ones in the
    order of a hash over all columns.
    """
    key = lambda name: F.coalesce(F.concat(F.lit("v"), F.col(name).cast("string")), F.lit("n"))
    plan = mixture(docs, id_col, text_col, source_col, **options).where(F.col("copies") > 0)
    chosen = materialize(
        plan.groupBy(key("doc_id").alias("__id"), F.col("text_hash").alias("__hash"), key("source").alias("__src"))
        .agg(F.max("copies").cast("int").alias("__most"), F.sum("copies").alias("__all"), F.count(F.lit(1)).alias("__rows")),
        "chosen",
    )
    marked = docs.withColumns({"__id": key(id_col), "__hash": F.xxhash64(text_col), "__src": key(source_col)})
    own = F.xxhash64(*[F.col(f.name) for f in docs.schema.fields if "map" not in f.dataType.simpleString()])
    joined = marked.join(chosen, ["__id", "__hash", "__src"]).withColumn("__own", own)
    # copies of rows that tie differ by one at most: the first rows take the larger number
    nth = F.row_number().over(Window.partitionBy("__id", "__hash", "__src").orderBy("__own"))
    larger = F.col("__all") - (F.col("__most") - 1) * F.col("__rows")
    taken = F.when(F.col("__nth") <= larger, F.col("__most")).when(F.col("__nth") <= F.col("__rows"), F.col("__most") - 1).otherwise(0)
    counted = joined.withColumn("__nth", nth).withColumn("__copies", taken.cast("int")).where("__copies > 0")
    return counted.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies")))).select(*docs.columns)


def op10_mixing(spark, sf_dir: str) -> DataFrame:
    return mixture(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "size", "source_size", "target", "taken")


OP10_SQL = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
         -ln((('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), 'null') || ':' || md5(coalesce(text, ''))), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0)
           / greatest(0.05, 1.0 - 4.0 * (length(coalesce(text, '')) - length(translate(coalesce(text, ''), '!|*#%&$', '')))
                                     / greatest(length(coalesce(text, '')), 1)) AS key
  FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source
), r AS (
  SELECT *, [5.0, 2.0, 1.0][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)]::DOUBLE AS w, source_size * 3.0::DOUBLE AS cap FROM s
), f AS (
  SELECT *, cap / w AS r, sum(cap) OVER o - cap AS filled, sum(w) OVER () - sum(w) OVER o + w AS open, sum(source_size::DOUBLE) OVER () AS total
  FROM r WINDOW o AS (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)
), l AS (
  SELECT arg_min((total - filled) / open, r) AS level FROM f WHERE (total - filled) / open <= r
), t AS (
  SELECT source, source_size, least(cap, level * w) AS target,
         CASE WHEN source_size > 0 THEN floor((least(cap, level * w) + 1e-6) / source_size) ELSE 0 END AS epochs
  FROM f, l
), u AS (
  SELECT d.*, t.source_size, t.target, t.epochs, t.target - t.epochs * t.source_size AS budget,
         sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target,
       CAST(size * (epochs + CASE WHEN epochs < 3 AND size > 0 AND (upto <= budget OR (budget - (upto - size) > 0 AND upto - budget < budget - (upto - size)))
                             THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM u
"""
