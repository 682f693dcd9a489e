"""Similarities of a point to the feedback vector and to another point, by attribute.

``sims`` of a facet attribute compare a value with the vector's slice of that attribute;
numeric, text and vector attributes have functions of their own. The overall similarity is
the mean over attributes; a missing attribute is skipped, or 0 with missing="zero".
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: (weight of the value, largest weight of the attribute, norm of the slice, touched values of the attribute) -> similarity
SIM: dict[str, Callable[[Column, Column, Column, Column], Column]] = {
    "share_of_max": lambda w, top, norm, touched: F.coalesce(F.try_divide(w, top), F.lit(0.0)),
    "weight": lambda w, top, norm, touched: w,
    "cosine": lambda w, top, norm, touched: F.coalesce(F.try_divide(w, norm), F.lit(0.0)),
    "jaccard": lambda w, top, norm, touched: F.when(w > 0, F.coalesce(F.try_divide(F.lit(1.0), touched.cast("double")), F.lit(0.0))).otherwise(F.lit(0.0)),
}


def register_sim(name: str, fn: Callable[[Column, Column, Column, Column], Column]) -> None:
    if name in SIM:
        raise ValueError(f"{name!r} is taken")
    SIM[name] = fn


def numeric_sim(value: Column, expected: Column, span: Column) -> Column:
    """1 at the expected value, falling to 0 over the range."""
    return F.greatest(F.lit(0.0), 1 - F.coalesce(F.try_divide(F.abs(value - expected), span), F.lit(0.0)))


def token_jaccard(a: Column, b: Column) -> Column:
    """Of two arrays of words as sets."""
    union = F.size(F.array_union(a, b))
    return F.coalesce(F.try_divide(F.size(F.array_intersect(a, b)).cast("double"), union), F.lit(0.0))


def edit_sim(a: Column, b: Column) -> Column:
    longest = F.greatest(F.length(a), F.length(b))
    return 1 - F.coalesce(F.try_divide(F.levenshtein(a, b).cast("double"), longest), F.lit(0.0))


def vector_cosine(a: Column, b: Column) -> Column:
    def dot(u: Column, v: Column) -> Column:
        return F.aggregate(F.zip_with(u, v, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, x: s + x)

    return F.coalesce(F.try_divide(dot(a, b), F.sqrt(dot(a, a) * dot(b, b))), F.lit(0.0))


def shared_facets(a: Column, b: Column) -> Column:
    """Share of attributes on which two signatures (arrays of attribute-value structs) agree."""
    return F.coalesce(F.try_divide(F.size(F.array_intersect(a, b)).cast("double"), F.greatest(F.size(a), F.size(b))), F.lit(0.0))


@dataclass(frozen=True)
class Attribute:
    """An attribute that isn't a facet: numeric (``span``: its range), tokens (an array of words), edit (a string) or vector."""

    attr: str
    column: str
    kind: str
    span: float = 1.0

    def similarity(self, a: Column, b: Column) -> Column:
        """Of two values; null if one is missing."""
        fn = {"numeric": lambda: numeric_sim(a, b, F.lit(float(self.span))), "tokens": lambda: token_jaccard(a, b), "edit": lambda: edit_sim(a, b), "vector": lambda: vector_cosine(a, b)}
        if self.kind not in fn:
            raise ValueError(f"unknown kind {self.kind!r}; one of {sorted(fn)}")
        return F.when(self.known(a, b), fn[self.kind]())

    def known(self, a: Column, b: Column) -> Column:
        return a.isNotNull() & b.isNotNull()

    def expected(self, met: DataFrame) -> DataFrame:
        """(session_id, expected_<attr>) of rows (session_id, column): the mean, the words of half the points or more, the commonest string, or the mean vector."""
        name, rows = f"expected_{self.attr}", met.where(F.col(self.column).isNotNull())
        by = rows.groupBy("session_id")
        if self.kind == "numeric":
            return by.agg(F.avg(self.column).alias(name))
        if self.kind == "edit":
            n = rows.groupBy("session_id", self.column).agg(F.count("*").alias("n"))
            return n.groupBy("session_id").agg(F.min_by(self.column, F.struct(-F.col("n"), self.column)).alias(name))
        if self.kind == "tokens":
            words = rows.select("session_id", F.explode(F.array_distinct(self.column)).alias("w")).groupBy("session_id", "w").agg(F.count("*").alias("n"))
            half = words.join(by.agg(F.count("*").alias("of")), "session_id").where(2 * F.col("n") >= F.col("of"))
            return rows.select("session_id").distinct().join(half.groupBy("session_id").agg(F.array_sort(F.collect_list("w")).alias(name)), "session_id", "left").withColumn(name, F.coalesce(name, F.array().cast("array<string>")))
        if self.kind == "vector":
            cells = rows.select("session_id", F.posexplode(self.column).alias("k", "v")).groupBy("session_id", "k").agg(F.avg("v").alias("v"))
            return cells.groupBy("session_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "v"))), lambda s: s["v"]).alias(name))
        raise ValueError(f"unknown kind {self.kind!r}")
