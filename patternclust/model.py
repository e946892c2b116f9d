"""Graphs as data: schemas, the compact row, its normal form, and validation.

A graph without direction, with labels on vertices and edges, is one row: vertex labels, and for
each edge its two ends (by position, smaller first) and label. Whatever is asked of single
graphs then stays within the row and needs no exchange.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

GRAPH_SCHEMA = "graph_id bigint, vl array<string>, eu array<int>, ew array<int>, el array<string>"


@dataclass
class Graph:
    """A small graph in memory: labels and, for each vertex, its neighbours with edge labels."""

    labels: list
    adj: list[dict] = field(default_factory=list)

    def __post_init__(self):
        if not self.adj:
            self.adj = [{} for _ in self.labels]

    @classmethod
    def of(cls, labels, eu=(), ew=(), el=()) -> Graph:
        g = cls(list(labels))
        for u, w, label in zip(eu, ew, el, strict=True):
            g.link(u, w, label)
        return g

    def link(self, u: int, w: int, label) -> None:
        self.adj[u][w] = self.adj[w][u] = label

    def add(self, label) -> int:
        self.labels.append(label)
        self.adj.append({})
        return len(self.labels) - 1

    @property
    def n_edges(self) -> int:
        return sum(map(len, self.adj)) // 2

    @property
    def size(self) -> int:
        return len(self.labels) + self.n_edges

    def edges(self):
        return [(u, w, label) for u, near in enumerate(self.adj) for w, label in near.items() if u < w]

    def edge_columns(self):
        own = sorted(self.edges())
        return [e[0] for e in own], [e[1] for e in own], [e[2] for e in own]

    def copy(self) -> Graph:
        return Graph(list(self.labels), [dict(x) for x in self.adj])

    def row(self) -> tuple:
        return (list(self.labels), *self.edge_columns())


def graph_rows(batch):
    """``(vl, eu, ew, el)`` as Python lists for each row of an Arrow batch or table; columns are unpacked whole, labels shared."""

    def lists(column):
        column = column.combine_chunks() if hasattr(column, "combine_chunks") else column
        values = column.flatten()
        if str(values.type).endswith("string"):
            coded = values.dictionary_encode()
            names = coded.dictionary.to_pylist()
            values = [names[i] for i in coded.indices.to_numpy(zero_copy_only=False).tolist()]
        else:
            values = values.to_pylist()
        at = 0
        for n in column.value_lengths().to_pylist():
            yield values[at : at + (n or 0)]
            at += n or 0

    names = batch.schema.names
    return zip(*(lists(batch.column(names.index(c))) for c in ("vl", "eu", "ew", "el")), strict=True)


def assemble(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """Compact graphs from ``vertices(g, v, l)`` and ``edges(g, a, b, l)``; both sides meet by graph once.

    Loops are left out; of edges between the same two vertices the smallest label stays.
    """
    v = vertices.groupBy("g").agg(F.sort_array(F.collect_set(F.struct("v", "l"))).alias("vs"))
    tidy = edges.where(F.col("a") != F.col("b")).select("g", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "l")
    e = tidy.groupBy("g", "a", "b").agg(F.min("l").alias("l")).groupBy("g").agg(F.sort_array(F.collect_list(F.struct("a", "b", "l"))).alias("es"))
    both = v.join(e, "g", "left").withColumn("es", F.coalesce("es", F.array().cast("array<struct<a:string,b:string,l:string>>")))
    at = lambda x: (F.array_position(F.col("vs.v"), x) - 1).cast("int")
    ends = F.transform("es", lambda x: F.struct(at(x["a"]).alias("i"), at(x["b"]).alias("j"), x["l"].alias("l")))
    both = both.withColumn("ends", F.transform(ends, lambda x: F.struct(F.least(x["i"], x["j"]).alias("u"), F.greatest(x["i"], x["j"]).alias("w"), x["l"].alias("l"))))
    return both.select(F.col("g").alias("graph_id"), F.col("vs.l").alias("vl"), F.col("ends.u").alias("eu"), F.col("ends.w").alias("ew"), F.col("ends.l").alias("el"))


def with_size(graphs: DataFrame) -> DataFrame:
    return graphs.withColumn("gsize", F.size("vl") + F.size("eu"))


def triples(graphs: DataFrame) -> DataFrame:
    """Length-1 paths ``(graph_id, la, le, lb)`` with la <= lb, without an exchange."""
    e = F.explode(F.arrays_zip("eu", "ew", "el")).alias("e")
    ends = graphs.select("graph_id", "vl", e).select("graph_id", F.element_at("vl", F.col("e.eu") + 1).alias("x"), F.element_at("vl", F.col("e.ew") + 1).alias("y"), F.col("e.el").alias("le"))
    return ends.select("graph_id", F.least("x", "y").alias("la"), "le", F.greatest("x", "y").alias("lb"))


def normal_form(graphs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``vertices(g, v, l)`` and ``edges(g, a, b, l)`` with positions as vertices."""
    v = graphs.select(F.col("graph_id").alias("g"), F.posexplode("vl").alias("v", "l"))
    e = graphs.select(F.col("graph_id").alias("g"), F.explode(F.arrays_zip("eu", "ew", "el")).alias("e"))
    return v, e.select("g", F.col("e.eu").alias("a"), F.col("e.ew").alias("b"), F.col("e.el").alias("l"))


def label_alphabet(graphs: DataFrame) -> DataFrame:
    """``(kind, label, code)``: the finite label set, coded by order."""
    from pyspark.sql import Window

    v = graphs.select(F.lit("v").alias("kind"), F.explode("vl").alias("label"))
    e = graphs.select(F.lit("e").alias("kind"), F.explode("el").alias("label"))
    return v.unionByName(e).distinct().withColumn("code", F.row_number().over(Window.partitionBy("kind").orderBy("label")) - 1)


def violations(graphs: DataFrame) -> DataFrame:
    """Rows that break the form: ends out of range or order, loops, double edges, arrays of different lengths."""
    pairs = F.arrays_zip("eu", "ew")
    bad = (
        (F.size("eu") != F.size("ew")) | (F.size("eu") != F.size("el"))
        | F.exists(pairs, lambda p: (p["eu"] < 0) | (p["eu"] >= p["ew"]) | (p["ew"] >= F.size("vl")))
        | (F.size(F.array_distinct(pairs)) != F.size(pairs))
    )
    return graphs.where(bad)


def to_text(graphs: DataFrame) -> DataFrame:
    v = F.transform("vl", lambda x, i: F.concat_ws(" ", F.lit("v"), i.cast("string"), x))
    e = F.transform(F.arrays_zip("eu", "ew", "el"), lambda x: F.concat_ws(" ", F.lit("e"), x["eu"].cast("string"), x["ew"].cast("string"), x["el"]))
    head = F.concat(F.lit("t # "), F.col("graph_id").cast("string"))
    return graphs.select(F.concat_ws("\n", F.array(head), v, e).alias("value"))


def from_text(blocks: DataFrame) -> DataFrame:
    """Compact graphs from blocks ``id\\nv ...\\ne ...``; labels may hold spaces."""
    lines = F.split(F.trim("value"), "\n")
    pick = lambda kind: F.filter("lines", lambda x: F.startswith(x, F.lit(kind + " ")))
    word = lambda x, i: F.element_at(F.split(x, " ", i + 1), i)
    held = blocks.withColumn("lines", lines).withColumn("vs", pick("v")).withColumn("es", pick("e"))
    by_place = F.array_sort(F.transform("vs", lambda x: F.struct(word(x, 2).cast("int").alias("i"), F.element_at(F.split(x, " ", 3), 3).alias("l"))))
    return held.select(
        F.trim(F.element_at("lines", 1)).cast("bigint").alias("graph_id"),
        F.transform(by_place, lambda x: x["l"]).alias("vl"),
        F.transform("es", lambda x: F.least(word(x, 2).cast("int"), word(x, 3).cast("int"))).alias("eu"),
        F.transform("es", lambda x: F.greatest(word(x, 2).cast("int"), word(x, 3).cast("int"))).alias("ew"),
        F.transform("es", lambda x: F.element_at(F.split(x, " ", 4), 4)).alias("el"),
    ).where(F.col("graph_id").isNotNull())
