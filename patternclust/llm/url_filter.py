"""URL filter: rules first, then logistic regression on hashed character n-grams.

Features and scores are DataFrame expressions only. The labelled table is small by contract
(checked); its hashed features are fetched and the weights fitted on the driver in plain Python.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
BUCKETS = 1 << 14
SIZES = (3, 4)
#: (host, path, verdict); a rule fits its host and all subdomains
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))

# Words of hosts and paths in the default labelled table.
BAD_WORDS = ("casino", "poker", "jackpot", "bets", "pills", "viagra", "xxx", "porn", "adult", "escort", "spam", "linkfarm", "ads", "tracker", "cheap", "warez", "torrent", "payday", "replica", "prizes", "winner")
GOOD_WORDS = (
    "library", "museum", "university", "school", "news", "weather", "research", "science", "history", "garden", "recipes", "travel", "health", "docs", "journal", "archive",
    "music", "theatre", "city", "maps", "nature", "books", "language", "kitchen", "mountain", "river", "physics", "teacher", "student", "painting", "railway", "football",
    "thesis", "station", "northern", "another", "bridge", "forest", "letters", "morning", "engine", "harbour", "island", "village", "winter", "summer", "orchestra", "chess",
)


def default_labels(spark: SparkSession) -> DataFrame:
    """``(url, label)``: 1 is to be blocked. A few hundred URLs made from the two word lists by rule; both classes
    get the same subdomains, languages, numbers and parameters, so that only the words tell them apart."""
    heads, tails = ("www.", "m.", "blog.", ""), ("/", "/en/{}", "/de/{}.html", "/fr/{}?page=2&ref=x", "/es/{}#top", "/en/{}/?utm_source=feed")
    rows = []
    for label, words in ((1, BAD_WORDS), (0, GOOD_WORDS)):
        for i, word in enumerate(words):
            for j in range(6):
                other = words[(5 * i + 3 * j + 1) % len(words)]
                host = (word, f"{word}-{other}", f"{other}-{word}", f"{word}{other}", f"{word}-x", f"{word}-net")[j]
                rows.append((f"https://{heads[(i + j) % 4]}{host}.example.{('com', 'org', 'net')[(i + j) % 3]}" + tails[(i + 2 * j) % 6].format(97 * i + 13 * j), label))
            rows.append((f"http://site{i}.example.org/{word}/{other}", label))
    return spark.createDataFrame(rows, "url string, label int")


def with_host_path(df: DataFrame, url_col: str = "url", host: str = "host", path: str = "path") -> DataFrame:
    """Adds host (A-Z lower-cased) and path; both empty where the url is null or has no ``://``."""
    split = r"://([^/?#]*)([^?#]*)"
    url = F.coalesce(F.col(url_col), F.lit(""))
    return df.withColumns(
        {host: F.translate(F.regexp_extract(url, split, 1), UPPER, UPPER.lower()), path: F.regexp_extract(url, split, 2)}
    )


def matched_rule(host, path, rules=RULES):
    """``(rule, verdict)`` columns of the longest rule that fits, else nulls."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for name, prefix, what in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == name) | F.endswith(host, F.lit("." + name))) & F.startswith(path, F.lit(prefix))
        rule, verdict = F.when(fits, F.lit(name + prefix)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def hashed_grams(host, path, buckets: int = BUCKETS):
    """Array of the buckets of all character n-grams, host and path hashed apart."""

    def grams(tag, text, n):
        last = F.length(text) - n + 1
        places = F.sequence(F.lit(0), F.greatest(last, F.lit(1)) - 1)
        gram = lambda chars, i: F.concat(*[F.get(chars, i + j) for j in range(n)])
        mark = lambda chars, i: F.pmod(F.xxhash64(F.lit(tag), gram(chars, i)), F.lit(buckets)).cast("int")
        # characters are parted once, as the variable of an outer lambda: a substring by position walks a long url from its start each time
        each = F.flatten(F.transform(F.array(F.split(text, "")), lambda chars: F.transform(places, lambda i: mark(chars, i))))
        return F.when(last >= 1, each).otherwise(F.array().cast("array<int>"))

    bounded = {"h": F.concat(F.lit("^"), host, F.lit("$")), "p": F.concat(path, F.lit("$"))}
    return F.concat(*[grams(tag, text, n) for tag, text in bounded.items() for n in SIZES])


def train(labels: DataFrame, buckets: int = BUCKETS, max_rows: int = 20000, epochs: int = 40, rate: float = 0.5, decay: float = 1e-4):
    """``(weights, bias)`` from ``(url, label)``; more than ``max_rows`` labelled rows is an error. Rows without a 0/1 label
    are left out; no rows: zero weights, so every url scores a half."""
    known = with_host_path(labels.where(F.col("label").isin(0, 1)).select("url", "label"))
    rows = known.select(hashed_grams(F.col("host"), F.col("path"), buckets).alias("grams"), "label").limit(max_rows + 1).collect()
    if len(rows) > max_rows:
        raise ValueError(f"the labelled table has more than {max_rows} rows")
    rows = sorted((r["grams"], r["label"]) for r in rows)
    weights, bias = [0.0] * buckets, 0.0
    for epoch in range(epochs):
        step = rate / (1 + epoch / 8)
        for k in range(len(rows)):
            grams, label = rows[(k * 7919 + epoch) % len(rows)] if len(rows) % 7919 else rows[k]
            scale = 1 / math.sqrt(max(1, len(grams)))
            z = bias + scale * sum(weights[g] for g in grams)
            off = label - 1 / (1 + math.exp(-max(-60.0, min(60.0, z))))
            for g in grams:
                weights[g] += step * (off * scale - decay * weights[g])
            bias += 0.1 * step * off
    return weights, bias


def block_probability(host, path, model):
    """Column with the probability that a url is to be blocked."""
    weights, bias = model
    table = F.split(F.lit(",".join(repr(w) for w in weights)), ",").cast("array<double>")
    grams = hashed_grams(host, path, len(weights))
    total = F.aggregate(grams, F.lit(0.0), lambda s, g: s + F.element_at(table, g + 1))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-(F.lit(bias) + total / F.sqrt(F.greatest(F.size(grams), F.lit(1))))))


def judge_urls(pages: DataFrame, model=None, rules=RULES, url_col: str = "url", id_col: str = "page_id", threshold: float = 0.5) -> DataFrame:
    """``(page_id, host, path, rule, verdict, p_block)`` for each row; a rule's verdict wins over the method's.

    Null, empty or malformed urls have empty host and path and are judged by the method; ids pass through as they
    are, repeated or null; other columns are ignored; an empty table gives an empty result.
    """
    model = model or train(default_labels(pages.sparkSession))
    parts = with_host_path(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url")))
    rule, verdict = matched_rule(F.col("host"), F.col("path"), rules)
    scored = parts.select(
        "page_id", "host", "path", rule.alias("rule"), verdict.alias("ruled"), block_probability(F.col("host"), F.col("path"), model).alias("p_block")
    )
    by_method = F.when(F.col("p_block") >= threshold, F.lit("block")).otherwise(F.lit("allow"))
    return scored.select("page_id", "host", "path", "rule", F.coalesce("ruled", by_method).alias("verdict"), "p_block")


def op5_url_filter(spark, sf_dir: str) -> DataFrame:
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet")).select("page_id", "host", "path", "rule", "verdict")
