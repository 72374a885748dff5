"""Degrees, Laplacians and eigenvalue counts on band form, inside the JVM.

A row has ``n`` symbols, ``adj`` (n - 1 weights) and ``skip`` (n - 2 weights).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from cutseg.functions.units import symbols

#: Eigenvalues up to cut * (1 + SLACK) + TINY count as within the cut.
SLACK, TINY = 1e-12, 1e-13


def _at(name: str, i: Column) -> Column:
    """Element i of an array, counted from 0; 0 outside."""
    return F.coalesce(F.get(name, i), F.lit(0.0))


def _index(n: str = "n") -> Column:
    return F.sequence(F.lit(0), F.col(n) - 1)


def with_degrees(bands: DataFrame, self_loop: float = 1.0) -> DataFrame:
    """Add ``deg``: each symbol's row sum, the self-loop included."""
    d = F.transform(_index(), lambda i: F.lit(float(self_loop)) + _at("adj", i - 1) + _at("adj", i) + _at("skip", i - 2) + _at("skip", i))
    return bands.withColumn("deg", d)


def laplacian(bands: DataFrame, form: str = "plain", self_loop: float = 1.0) -> DataFrame:
    """Add ``l0, l1, l2``: the main, first and second diagonal of D - W, or of
    the symmetric normalised form."""
    b = with_degrees(bands, self_loop)
    one, two = F.col("n") - 1, F.col("n") - 2
    some = lambda n, f: F.when(n > 0, F.transform(F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0))), f)).otherwise(F.array().cast("array<double>"))
    if form == "plain":
        return b.withColumns({"l0": F.transform("deg", lambda d: d - self_loop), "l1": some(one, lambda i: -_at("adj", i)), "l2": some(two, lambda i: -_at("skip", i))})
    root = lambda i, j: F.sqrt(F.get("deg", i) * F.get("deg", j))
    zero = lambda c: F.coalesce(c, F.lit(0.0))  # noqa: E731  a symbol without any weight keeps a zero row
    return b.withColumns({
        "l0": F.transform("deg", lambda d: F.when(d > 0, 1 - self_loop / d).otherwise(0.0)),
        "l1": some(one, lambda i: zero(-_at("adj", i) / F.nullif(root(i, i + 1), F.lit(0.0)))),
        "l2": some(two, lambda i: zero(-_at("skip", i) / F.nullif(root(i, i + 2), F.lit(0.0))))})


def count_below(cut: Column) -> Column:
    """How many eigenvalues of the matrix ``l0, l1, l2`` are at most ``cut``: the
    negative pivots of its shifted LDL' factorisation, no eigenvector needed."""
    x = cut * (1 + SLACK) + TINY
    zero = F.lit(0.0)
    start = F.struct(zero.alias("d1"), zero.alias("p1"), zero.alias("q1"), zero.alias("d2"), zero.alias("q2"), F.lit(0).alias("k"))

    def step(s: Column, i: Column) -> Column:
        d = F.get("l0", i) - x - s["p1"] * s["p1"] * s["d1"] - s["q2"] * s["q2"] * s["d2"]
        d = F.when(d == 0, F.lit(1e-300)).otherwise(d)
        p = (_at("l1", i) - s["p1"] * s["q1"] * s["d1"]) / d
        return F.struct(d.alias("d1"), p.alias("p1"), (_at("l2", i) / d).alias("q1"), s["d1"].alias("d2"), s["q1"].alias("q2"), (s["k"] + F.when(d < 0, 1).otherwise(0)).alias("k"))

    return F.aggregate(_index(), start, step, lambda s: s["k"])


def components(bands: DataFrame) -> DataFrame:
    """Add ``n_components``: 1 + the places that no edge crosses."""
    open_ = F.filter(F.sequence(F.lit(0), F.greatest(F.col("n") - 2, F.lit(0))), lambda i: (i < F.col("n") - 1) & (_at("adj", i) == 0) & (_at("skip", i - 1) == 0) & (_at("skip", i) == 0))
    return bands.withColumn("n_components", F.when(F.col("n") > 0, 1 + F.size(open_)).otherwise(0))


#: Stands between words while they are one string; a code point that is no character.
_MARK = "\U0010ffff"


def cut_words(s: Column, is_cut) -> Column:
    """Words of ``s`` when a boundary follows symbol i wherever ``is_cut(i)``.

    Linear in the symbols, as ``is_cut`` is asked once for each of them."""
    marked = F.transform(symbols(s), lambda c, i: F.when(is_cut(i), F.concat(c, F.lit(_MARK))).otherwise(c))
    joined = F.rtrim(F.array_join(marked, ""), F.lit(_MARK))  # nothing follows the last symbol
    return F.when(F.length(s) > 0, F.split(joined, _MARK)).otherwise(F.array().cast("array<string>"))
