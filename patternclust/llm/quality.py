"""Quality classifier by positive-unlabelled learning with the non-negative risk.

A linear model over standardised text statistics is trained on trusted positives and unlabelled
web text. The risk is prior * E_p[loss(+)] + max(0, E_u[loss(-)] - prior * E_p[loss(-)]) with the
logistic loss; where the bracket is negative its gradient is reversed. The class prior is
estimated from the trusted positives and the unlabelled texts: negative labels are never read.
"""

from __future__ import annotations

import operator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

MARKS = b"!|*#%&$@<>{}[]()=/\\:;-_.,?\"'+~^`"
SHARES = 15 + len(MARKS)
WIDTH = 2 * SHARES + 2


def statistics(text: bytes | None) -> np.ndarray:
    """Fixed-width description of a whole text; null as empty."""
    text = text or b""
    n = max(1, len(text))
    seen = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    words = text.split()
    w = max(1, len(words))
    lines = text.split(b"\n")
    sizes = list(map(len, words))
    upper, lower = int(seen[65:91].sum()), int(seen[97:123].sum())
    shares = [
        1 - len(set(words)) / w,
        sum(map(operator.eq, words, words[1:])) / w,
        1 - len(set(zip(words, words[1:]))) / w,
        sum(map(operator.eq, words, words[2:])) / w,
        upper / max(1, upper + lower),
        sum(map(bytes.isupper, words)) / w,
        int(seen[48:58].sum()) / n,
        int(seen[128:].sum()) / n,
        int(seen[10]) / n,
        1 - len(set(lines)) / len(lines),
        sizes.count(1) / w,
        sum(1 for k in sizes if k > 15) / w,
        sum(1 for k in sizes if k > 40) / w,
        int(seen[:9].sum() + seen[14:32].sum()) / n,
        1 - int(upper + lower + seen[128:].sum() + seen[32]) / n,
    ] + (seen[list(MARKS)] / n).tolist()
    shares = np.array(shares)
    return np.concatenate([shares, np.log1p(100 * shares), [np.log1p(len(words)) / 10, np.log1p(sum(sizes) / w)]])


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8) @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def fit_nnpu(positive: np.ndarray, unlabelled: np.ndarray, prior: float, rounds: int = 600, rate: float = 0.05, decay: float = 1e-3) -> QualityModel:
    """Minimise the non-negative risk by full-batch Adam steps; deterministic."""
    both = np.concatenate([positive, unlabelled])
    mean, scale = both.mean(axis=0), both.std(axis=0) + 1e-6
    p, u = (np.clip((x - mean) / scale, -8, 8) for x in (positive, unlabelled))
    p, u = (np.c_[x, np.ones(len(x))] for x in (p, u))
    theta, m, v = np.zeros(p.shape[1]), np.zeros(p.shape[1]), np.zeros(p.shape[1])
    keep = np.r_[np.ones(p.shape[1] - 1), 0.0]
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))
    for step in range(1, rounds + 1):
        gp, gu = p @ theta, u @ theta
        plus = -prior * (p.T @ sigmoid(-gp)) / len(p)
        minus = (u.T @ sigmoid(gu)) / len(u) - prior * (p.T @ sigmoid(gp)) / len(p)
        bracket = np.logaddexp(0, gu).mean() - prior * np.logaddexp(0, gp).mean()
        grad = (plus + minus if bracket >= 0 else -minus) + decay * keep * theta
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        theta -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return QualityModel(mean, scale, theta[:-1], float(theta[-1]), prior)


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, sure: float = 0.9) -> float:
    """Share of positives among the unlabelled: the smallest ratio of unlabelled to positive rows above a score.

    A model learned from every second row scores the others. Above any score, unlabelled rows hold at least the share of
    positives times the part of positives there; where only positives are left the ratio is the share itself. The score is chosen with the
    errors of both parts added (at confidence ``sure``), so that few rows far up do not decide.
    """
    model = fit_nnpu(positive[::2], unlabelled[::2], 0.5, rounds=300)
    p, u = np.sort(model.scores(positive[1::2])), np.sort(model.scores(unlabelled[1::2]))
    if not len(p) or not len(u):
        return 0.5
    above_p = 1 - np.arange(len(p)) / len(p)
    above_u = 1 - np.searchsorted(u, p) / len(u)
    doubt = sum(np.sqrt(np.log(4 / (1 - sure)) / (2 * len(x))) for x in (p, u))
    best = int(np.argmin(above_u / above_p + doubt / above_p))
    return float(np.clip(above_u[best] / above_p[best], 0.01, 0.99))


def held_out(id_col):
    """True where crc32 of the id as text leaves 0 when divided by 5; a null id: false."""
    return F.coalesce(F.crc32(id_col.cast("string")) % 5 == 0, F.lit(False))


def train(
    docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality",
    max_rows: int = 8000, prior: float | None = None, seed: int = 7,
) -> QualityModel:
    """Learn from at most about ``max_rows`` trusted positives and as many unlabelled texts, drawn by
    a hash of the id; only these rows' statistics reach the driver. Rows held out are not drawn, and of the labels only
    those of positives are read. ``prior`` None: estimated from both.

    No positives or no documents: a model that gives every text the prior, or a half.
    """
    known = labels.where((F.col(label_col) == 1) & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    n_positive, n_docs = known.count(), docs.count()
    part = lambda n, salt: F.pmod(F.xxhash64(F.col(id_col), F.lit(seed + salt)), F.lit(1 << 20)) < int(min(1.0, max_rows / max(n, 1)) * (1 << 20))
    trusted = known.where(part(n_positive, 0)).select(F.col(id_col).alias("__id"), F.lit(True).alias("trusted")).distinct()
    # trusted has max_rows rows or so by construction
    drawn = docs.select(F.col(id_col).alias("__id"), F.col(text_col).cast("binary").alias("t"), part(n_docs, 1).alias("any"))
    drawn = drawn.where(F.col("__id").isNotNull() & ~held_out(F.col("__id"))).join(F.broadcast(trusted), "__id", "left")
    drawn = drawn.where(F.col("trusted") | F.col("any")).select(F.coalesce("trusted", F.lit(False)).alias("p"), F.col("any").alias("u"), "t")

    def described(batches):
        for batch in batches:
            rows = [statistics(t).tolist() for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(rows, pa.list_(pa.float64()))], ["p", "u", "x"])

    got = drawn.mapInArrow(described, "p boolean, u boolean, x array<double>").toArrow()
    x = np.array(got.column("x").to_pylist(), dtype=float).reshape(-1, WIDTH)
    p, u = (np.array(got.column(c).to_pylist(), dtype=bool) for c in ("p", "u"))
    if not p.any() or not u.any():
        prior = 0.5 if prior is None else prior
        return QualityModel(np.zeros(WIDTH), np.ones(WIDTH), np.zeros(WIDTH), float(np.log((prior + 1e-6) / (1 - prior + 1e-6))), prior)
    order = np.lexsort(x.T)  # sums run in one order whatever the partitions
    x, p, u = x[order], p[order], u[order]
    return fit_nnpu(x[p], x[u], estimate_prior(x[p], x[u]) if prior is None else prior)


def score(docs: DataFrame, model: QualityModel, text_col: str = "text", out: str = "score") -> DataFrame:
    """``docs`` with a column ``out``: probability-like quality of each whole text; null as empty; a column of that name is replaced."""
    at = docs.columns.index(text_col)
    held = [i for i, c in enumerate(docs.columns) if c.lower() != out.lower()]
    names = [*(docs.columns[i] for i in held), out]
    schema = T.StructType([*(docs.schema.fields[i] for i in held), T.StructField(out, T.DoubleType())])

    def kernel(batches):
        for batch in batches:
            texts = batch.column(at).cast(pa.binary()).to_pylist()
            x = np.array([statistics(t) for t in texts]).reshape(-1, WIDTH)
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in held), pa.array(model.scores(x))], names)

    return docs.mapInArrow(kernel, schema)


def drop_low_quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """``docs`` without the rows scored under ``threshold``; all columns kept."""
    return score(docs, train(docs, labels), out="__score").where(F.col("__score") >= threshold).drop("__score")


def op7_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, model).select(
        "doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted")
    )
