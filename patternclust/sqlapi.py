"""SQL functions over compact graphs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions import canon, fingerprint, iso, mcs
from .functions.binomial import decide
from .model import Graph

GRAPH = "struct<vl:array<string>,eu:array<int>,ew:array<int>,el:array<string>>"


def _graphs(part: pd.DataFrame) -> list[Graph]:
    return [Graph.of(*row) for row in zip(part["vl"], part["eu"], part["ew"], part["el"])]


@F.pandas_udf(T.BooleanType())
def graph_contains(host: pd.DataFrame, pattern: pd.DataFrame) -> pd.Series:
    return pd.Series([iso.contains(h, p) for h, p in zip(_graphs(host), _graphs(pattern))])


@F.pandas_udf(T.BinaryType())
def graph_code(g: pd.DataFrame) -> pd.Series:
    return pd.Series([canon.code(x) for x in _graphs(g)])


@F.pandas_udf(T.IntegerType())
def graph_mcs(a: pd.DataFrame, b: pd.DataFrame) -> pd.Series:
    return pd.Series([mcs.size(x, y) for x, y in zip(_graphs(a), _graphs(b))])


@F.pandas_udf(T.ArrayType(T.LongType()))
def graph_fingerprint(g: pd.DataFrame) -> pd.Series:
    return pd.Series([fingerprint.to_words(fingerprint.fingerprint(x)) for x in _graphs(g)])


@F.pandas_udf(T.StringType())
def support_decision(k: pd.Series, n: pd.Series, minsup: pd.Series, alpha: pd.Series) -> pd.Series:
    return pd.Series([decide(int(a), int(b), float(c), float(d)) for a, b, c, d in zip(k, n, minsup, alpha)])


def register(spark: SparkSession) -> None:
    """graph_contains(host, pattern), graph_code(g), graph_mcs(a, b), graph_fingerprint(g), support_decision(k, n, minsup, alpha); a graph is
    named_struct('vl', vl, 'eu', eu, 'ew', ew, 'el', el)."""
    for f in (graph_contains, graph_code, graph_mcs, graph_fingerprint, support_decision):
        spark.udf.register(f.func.__name__, f)
