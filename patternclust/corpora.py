"""Graph corpora on the given tables, in normal form: ``vertices(g, v, l)`` and ``edges(g, a, b, l)``."""

from __future__ import annotations

from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .model import GRAPH_SCHEMA, assemble
from .sources.tables import table

Corpus = tuple[DataFrame, DataFrame]

# Function words of four languages that keep their names as vertex labels.
LISTED_WORDS = {
    "en": "the of and to in is that for it with as was on are by this".split(),
    "fr": "de la le et les des un une du dans que est pour qui sur pas".split(),
    "de": "der die und den von zu das mit sich des auf ist im dem nicht ein".split(),
    "es": "el que y los se del las por con para una su al lo como más".split(),
}
#: for guessing a language: ten words each
GUESS_WORDS = {k: v[:10] for k, v in LISTED_WORDS.items()}


def order_corpus(spark: SparkSession, sf: str) -> Corpus:
    """One graph per order with lines: the order, its parts and their suppliers."""
    line = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus")
    part = F.concat(F.lit("p"), "l_partkey")
    supplier = F.concat(F.lit("s"), "l_suppkey")
    orders = table(spark, sf, "orders").join(line.select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_semi")
    region = table(spark, sf, "supplier").join(table(spark, sf, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    v = (
        orders.select(F.col("o_orderkey").alias("g"), F.lit("o").alias("v"), F.col("o_orderpriority").alias("l"))
        .unionByName(line.join(table(spark, sf, "part"), F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_orderkey").alias("g"), part.alias("v"), F.col("p_type").alias("l")))
        .unionByName(line.join(region, F.col("l_suppkey") == F.col("s_suppkey")).select(F.col("l_orderkey").alias("g"), supplier.alias("v"), F.col("r_name").alias("l")))
    )
    e = line.select(F.col("l_orderkey").alias("g"), F.lit("o").alias("a"), part.alias("b"), F.col("l_returnflag").alias("l")).unionByName(
        line.select(F.col("l_orderkey").alias("g"), part.alias("a"), supplier.alias("b"), F.col("l_linestatus").alias("l"))
    )
    return v.distinct(), e.groupBy("g", "a", "b").agg(F.min("l").alias("l"))


def session_corpus(spark: SparkSession, sf: str) -> Corpus:
    """One graph per user and week: consecutive events, and events of one type in turn."""
    e = table(spark, sf, "events").select((F.col("user_id") * 100 + F.weekofyear("ts")).alias("g"), "event_id", "event_type", "ts")
    in_time = Window.partitionBy("g").orderBy("ts", "event_id")
    of_type = Window.partitionBy("g", "event_type").orderBy("ts", "event_id")
    e = e.withColumn("before", F.lag("event_id").over(in_time)).withColumn("alike", F.lag("event_id").over(of_type))
    v = e.select("g", F.col("event_id").cast("string").alias("v"), F.col("event_type").alias("l"))
    link = lambda c, label: e.where(F.col(c).isNotNull()).select("g", F.col(c).cast("string").alias("a"), F.col("event_id").cast("string").alias("b"), F.lit(label).alias("l"))
    same = e.where(F.col("alike").isNotNull() & (F.col("alike") != F.col("before")))
    return v, link("before", "next").unionByName(same.select("g", F.col("alike").cast("string").alias("a"), F.col("event_id").cast("string").alias("b"), F.lit("same").alias("l")))


def _document_labels(spark: SparkSession, sf: str) -> DataFrame:
    """``(g, t)``: each document's words in order, the listed ones by name and others by length class."""
    listed = [w for own in LISTED_WORDS.values() for w in own]
    bucket = lambda word: F.concat(F.lit("*"), F.least(F.lit(6), F.floor((F.length(word) + 1) / 2)).cast("string"))
    words = F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), 1)
    labels = F.transform(words, lambda w: F.when(w.isin(listed), w).otherwise(bucket(w)))
    return table(spark, sf, "documents").select(F.col("doc_id").alias("g"), labels.alias("t")).where(F.size("t") > 0)


def document_corpus(spark: SparkSession, sf: str) -> Corpus:
    """One graph per document, from its whole text: the listed words and length classes of other words in it; each is linked
    to what follows it most often (``a``) and to what comes two tokens later most often (``s``), the smaller of equals."""
    d = _document_labels(spark, sf)
    v = d.select("g", F.explode(F.array_distinct("t")).alias("l")).select("g", F.col("l").alias("v"), "l")

    def followers(step: int, label: str) -> DataFrame:
        pairs = F.arrays_zip(F.slice("t", 1, F.greatest(F.size("t") - step, F.lit(0))).alias("x"), F.slice("t", step + 1, F.size("t")).alias("y"))
        seen = d.select("g", F.explode(pairs).alias("p")).select("g", "p.x", "p.y").where("x <> y").groupBy("g", "x", "y").count()
        first = seen.groupBy("g", "x").agg(F.min(F.struct((-F.col("count")).alias("n"), "y")).alias("m"))
        return first.select("g", F.least("x", "m.y").alias("a"), F.greatest("x", "m.y").alias("b"), F.lit(label).alias("l"))

    e = followers(1, "a").unionByName(followers(2, "s"))
    return v, e.groupBy("g", "a", "b").agg(F.min("l").alias("l"))


def _lists(of: np.ndarray, n: int, values: pa.Array) -> pa.ListArray:
    return pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(np.bincount(of, minlength=n))]).astype(np.int32), values)


def document_batch(part: pa.RecordBatch) -> pa.RecordBatch:
    """Graphs of a few documents: followers are counted in a table of documents, words and words."""
    n, texts = part.num_rows, part.column(1).flatten()
    words = texts.flatten().dictionary_encode()
    names = words.dictionary.to_pylist()
    k, order = len(names), sorted(range(len(names)), key=names.__getitem__)
    rank = np.empty(k, dtype=np.int64)
    rank[order] = np.arange(k)
    codes = rank[words.indices.to_numpy()]
    text = np.repeat(np.arange(len(texts)), texts.value_lengths().to_numpy())
    graph = np.repeat(np.arange(n), part.column(1).value_lengths().to_numpy())[text]
    held = np.zeros((n, k), bool)
    held[graph, codes] = True
    keyed = part.column(0).is_valid().to_numpy(zero_copy_only=False)  # edges meet their vertices by key
    links = np.zeros((n, k, k), np.int8)
    for step, label in ((2, 2), (1, 1)):  # the smaller label of two stays
        near = np.flatnonzero((text[:-step] == text[step:]) & (codes[:-step] != codes[step:]) & keyed[graph[:-step]])
        counts = np.bincount((graph[near] * k + codes[near]) * k + codes[near + step], minlength=n * k * k).reshape(n * k, k)
        first = counts.argmax(1)  # of equal ones the smaller word
        at = np.flatnonzero(counts[np.arange(n * k), first])
        x, y = at % k, first[at]
        links[at // k, np.minimum(x, y), np.maximum(x, y)] = label
    (of, v), (g, a, b) = np.nonzero(held), np.nonzero(links)
    place = np.cumsum(held, 1, dtype=np.int32) - 1
    return pa.RecordBatch.from_arrays([
        part.column(0), _lists(of, n, pa.array([names[i] for i in order], pa.string()).take(pa.array(v))), _lists(g, n, pa.array(place[g, a])), _lists(g, n, pa.array(place[g, b])),
        _lists(g, n, pa.array(["", "a", "s"]).take(pa.array(links[g, a, b]))),
    ], ["graph_id", "vl", "eu", "ew", "el"])


def document_graphs(spark: SparkSession, sf: str) -> DataFrame:
    """The compact graphs of ``document_corpus``: labels meet by document once, the rest is within the row."""
    def kernel(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 400):  # labels are of a list of under a hundred
                yield document_batch(batch.slice(at, 400))

    return _document_labels(spark, sf).groupBy(F.col("g").cast("bigint").alias("g")).agg(F.collect_list("t").alias("ts")).mapInArrow(kernel, GRAPH_SCHEMA)


def conversation_corpus(spark: SparkSession, sf: str) -> Corpus:
    """One graph per conversation: turns in a row, and equal roles two turns apart."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = table(spark, sf, "conversations").select("conv_id", "turn", "role").distinct()
    c = c.withColumn("p1", F.lag("turn", 1).over(w)).withColumn("p2", F.lag("turn", 2).over(w)).withColumn("r2", F.lag("role", 2).over(w))
    v = c.select(F.col("conv_id").alias("g"), F.col("turn").cast("string").alias("v"), F.col("role").alias("l"))
    link = lambda rows, at, label: rows.select(F.col("conv_id").alias("g"), F.col(at).cast("string").alias("a"), F.col("turn").cast("string").alias("b"), F.lit(label).alias("l"))
    return v, link(c.where("p1 IS NOT NULL"), "p1", "next").unionByName(link(c.where("p2 IS NOT NULL AND r2 = role"), "p2", "same"))


class _Tree(HTMLParser):
    VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}

    def __init__(self, siblings: bool):
        super().__init__()
        self.labels, self.eu, self.ew, self.el, self.open, self.last, self.siblings = [], [], [], [], [], {}, siblings

    def handle_starttag(self, tag, attrs):
        at = len(self.labels)
        self.labels.append(tag)
        parent = self.open[-1][1] if self.open else -1
        if parent >= 0:
            self._edge(parent, at, "c")
        if self.siblings and parent in self.last:
            self._edge(self.last[parent], at, "s")
        self.last[parent] = at
        if tag not in self.VOID:
            self.open.append((tag, at))

    def handle_endtag(self, tag):
        for k in range(len(self.open) - 1, -1, -1):
            if self.open[k][0] == tag:
                del self.open[k:]
                return

    def _edge(self, u, w, label):
        self.eu.append(u)
        self.ew.append(w)
        self.el.append(label)


def dom_graphs(spark: SparkSession, sf: str, siblings: bool = False) -> DataFrame:
    """Compact element trees of pages; end tags without a start are passed over, open elements end with their parent."""
    import pyarrow as pa

    def kernel(batches):
        for batch in batches:
            rows = []
            for key, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                tree = _Tree(siblings)
                tree.feed(html or "")
                rows.append((key, tree.labels, tree.eu, tree.ew, tree.el))
            columns = list(zip(*rows, strict=True)) if rows else [[], [], [], [], []]
            kinds = (pa.int64(), pa.list_(pa.string()), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], ["graph_id", "vl", "eu", "ew", "el"])

    return table(spark, sf, "pages").select(F.col("page_id").alias("graph_id"), "html").mapInArrow(kernel, GRAPH_SCHEMA)


CORPORA = {"order": order_corpus, "session": session_corpus, "doc": document_corpus, "conv": conversation_corpus}


def graphs(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """Compact graphs of a corpus by name."""
    if name in ("dom", "doc"):
        return dom_graphs(spark, sf) if name == "dom" else document_graphs(spark, sf)
    return assemble(*CORPORA[name](spark, sf))
