"""Containment of small patterns as native column expressions over compact graphs."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _edges() -> Column:
    return F.arrays_zip("eu", "ew", "el")


def _label(i: Column) -> Column:
    return F.element_at("vl", i + 1)


def has_edge(la: str, le: str, lb: str) -> Column:
    """Whether the graph has an edge labelled ``le`` between vertices labelled ``la`` and ``lb``."""

    def fits(e):
        x, y = _label(e["eu"]), _label(e["ew"])
        return (e["el"] == le) & (((x == la) & (y == lb)) | ((x == lb) & (y == la)))

    return F.exists(_edges(), fits)


def has_path(la: str, le: str, lb: str, lf: str, lc: str) -> Column:
    """Whether it has the path la -le- lb -lf- lc over three different vertices."""

    def half(e, outer, inner, label):
        """Middle vertices reached from an ``outer`` end, as an array of (outer, middle)."""
        return F.flatten(
            F.transform(
                F.filter(e, lambda x: x["el"] == label),
                lambda x: F.filter(
                    F.array(F.struct(x["eu"].alias("o"), x["ew"].alias("m")), F.struct(x["ew"].alias("o"), x["eu"].alias("m"))),
                    lambda p: (_label(p["o"]) == outer) & (_label(p["m"]) == inner),
                ),
            )
        )

    left, right = half(_edges(), la, lb, le), half(_edges(), lc, lb, lf)
    return F.exists(left, lambda p: F.exists(right, lambda q: (p["m"] == q["m"]) & (p["o"] != q["o"])))


def triple_keys() -> Column:
    """The graph's edges as texts la|le|lb with la <= lb: a fingerprint that SQL has too."""
    return F.array_distinct(
        F.transform(_edges(), lambda e: F.concat_ws("|", F.least(_label(e["eu"]), _label(e["ew"])), e["el"], F.greatest(_label(e["eu"]), _label(e["ew"]))))
    )
