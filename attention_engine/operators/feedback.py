"""Facets, the feedback vector and the similarity of points to it.

The vector is a sparse table (session_id, attr, val, raw, weight). An update adds delta per
matched point and facet; nothing is ever taken away; weights are normalised after each
update and carried on, so delta matters from the second update.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.similarity import SIM, Attribute
from ..keep import keep
from .quadtree import placed


@dataclass(frozen=True)
class Facet:
    """How a column becomes attribute values: category, bins (lower edges, last open), many (an array)."""

    attr: str
    column: str
    kind: str = "category"
    edges: tuple = ()
    names: tuple = ()

    def value(self) -> Column:
        c = F.col(self.column)
        if self.kind == "bins":
            out = F.lit(self.names[0])
            for edge, name in zip(self.edges, self.names[1:], strict=True):
                out = F.when(c >= edge, F.lit(name)).otherwise(out)
            return F.when(c.isNotNull(), out)
        return c.cast("string")


def signature(spec: list[Facet]) -> Column:
    """The facets of a point as an array of (attr, val), missing ones left out."""
    one = [f for f in spec if f.kind != "many"]
    single = F.filter(F.array(*[F.struct(F.lit(f.attr).alias("attr"), f.value().alias("val")) for f in one]), lambda s: s["val"].isNotNull())
    many = [F.transform(F.array_distinct(F.coalesce(F.col(f.column), F.array().cast("array<string>"))), lambda v, f=f: F.struct(F.lit(f.attr).alias("attr"), v.alias("val"))) for f in spec if f.kind == "many"]
    return F.concat(single, *many) if many else single


def facetize(points: DataFrame, spec: list[Facet]) -> DataFrame:
    """(point_id, attr, val), long."""
    return points.select("point_id", F.explode(signature(spec)).alias("f")).select("point_id", "f.*")


def facet_domain(points: DataFrame, spec: list[Facet]) -> DataFrame:
    """All cells (attr, val); bins with their empty ones."""
    seen = facetize(points, spec).select("attr", "val").distinct()
    binned = [(f.attr, n) for f in spec if f.kind == "bins" for n in f.names]
    if binned:
        seen = seen.union(points.sparkSession.createDataFrame(binned, "attr string, val string")).distinct()
    return seen


def zero_vector(domain: DataFrame, sessions: DataFrame) -> DataFrame:
    """A row per session and cell: the dense form, whose size is that of its result."""
    return sessions.select("session_id").distinct().join(domain).select("session_id", "attr", "val", F.lit(0.0).alias("raw"), F.lit(0.0).alias("weight"))


def increments(found: DataFrame, facets: DataFrame, delta: float = 1.0) -> DataFrame:
    """(session_id, attr, val, add). ``facets`` has several rows a point, which Spark doesn't foresee, so it must not be broadcast."""
    return found.join(facets.hint("merge"), "point_id").groupBy("session_id", "attr", "val").agg((F.count("*") * F.lit(float(delta))).alias("add"))


def normalise(vector: DataFrame, how: str = "share") -> DataFrame:
    """Weights that sum to 1 a session, or stay 0 where nothing was ever added. softmax takes all rows given, so untouched cells must be among them."""
    w = Window.partitionBy("session_id")
    raw, total = F.col("raw"), F.sum("raw").over(w)
    if how == "share":
        out = F.try_divide(raw, total)
    elif how in ("softmax", "softmax_touched"):
        touched = F.lit(True) if how == "softmax" else raw > 0
        e = F.when(touched, F.exp(raw - F.max("raw").over(w))).otherwise(F.lit(0.0))
        return vector.withColumns({"e": e, "total": total}).withColumn("weight", F.when(F.col("total") > 0, F.col("e") / F.sum("e").over(w)).otherwise(F.lit(0.0))).drop("e", "total")
    else:
        raise ValueError(f"unknown normalisation {how!r}")
    return vector.withColumn("weight", F.coalesce(out, F.lit(0.0)))


def _added(vector: DataFrame | None, add: DataFrame, how: str, domain: DataFrame | None) -> DataFrame:
    """The vector after increments (session_id, attr, val, add), over all cells of the domain under softmax."""
    cell = ["session_id", "attr", "val"]
    raw = add.select(*cell, F.col("add").alias("raw"))
    if vector is not None:
        old = vector.select(*cell, F.col("weight").alias("old"))
        raw = old.join(add, cell, "full").select(*cell, (F.coalesce("old", F.lit(0.0)) + F.coalesce("add", F.lit(0.0))).alias("raw"))
    if how == "softmax":
        dense = zero_vector(domain, raw).select(*cell)
        raw = dense.join(raw, cell, "left").select(*cell, F.coalesce("raw", F.lit(0.0)).alias("raw"))
    return normalise(raw, how).select(*cell, "raw", "weight")


def update_feedback(vector: DataFrame | None, found: DataFrame, facets: DataFrame, delta: float = 1.0, how: str = "share", domain: DataFrame | None = None) -> DataFrame:
    """The vector after one update: raw = weight before + delta per point and facet. ``domain`` (attr, val): the cells of softmax; else those of ``facets``."""
    if how == "softmax" and domain is None:
        domain = facets.select("attr", "val").distinct()
    return _added(vector, increments(found, facets, delta), how, domain)


def falls(before: DataFrame, after: DataFrame) -> DataFrame:
    """Cells whose raw value fell below the weight before: none, by construction."""
    return before.select("session_id", "attr", "val", F.col("weight").alias("old")).join(after, ["session_id", "attr", "val"], "left").where(F.coalesce("raw", F.lit(0.0)) < F.col("old"))


#: Points that a tile holds on average.
PER_TILE = 2.0


def nearest_points(places: DataFrame, points: DataFrame, tile: float | None = None, reach: float | None = None) -> DataFrame:
    """(session_id, sample_id, point_id): the nearest point of each place, ties by id.

    Equal places ask once, and of equal points the smallest id answers. They meet on tiles,
    whose side (``tile``) follows from the number of points; what has no point within a
    tile's side looks again in tiles twice as wide, until all are answered or the side is
    ``reach`` (None: until the tile holds everything). A place or point without coordinates
    takes no part.
    """
    at = lambda c, side: F.floor(F.col(c) / side).cast("long")
    around = F.array(*[F.lit(k).cast("long") for k in (-1, 0, 1)])
    home = keep(points.where(placed()).groupBy(F.col("x").alias("px"), F.col("y").alias("py")).agg(F.min("point_id").alias("point_id")))
    d2 = (F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))
    asking = places.where(placed()).select("session_id", "sample_id", "x", "y")
    left, out = keep(asking.select("x", "y").distinct()), None
    n, *own = home.agg(F.count("*"), *[f(c) for c in ("px", "py") for f in (F.min, F.max)]).first()
    box = left.unionAll(home.select("px", "py")).agg(*[f(c) for c in ("x", "y") for f in (F.min, F.max)]).first()
    wide, high = (own[1] - own[0], own[3] - own[2]) if n else (0.0, 0.0)
    tile = tile or (wide * high * PER_TILE / n) ** 0.5 if n and wide * high > 0 else tile or max(wide, high) * PER_TILE / max(n, 1) or 50.0
    widest = 0.0 if box[0] is None or not n else max(box[1] - box[0], box[3] - box[2], tile)
    most = widest * 4 if reach is None else min(widest * 4, reach)
    side = float(tile) if reach is None else min(float(tile), float(reach))
    while True:
        sent = left.select("x", "y", F.explode(F.transform(around, lambda k: k + at("x", side))).alias("tx"), at("y", side).alias("ty0")).withColumn("ty", F.explode(F.transform(around, lambda k: k + F.col("ty0")))).drop("ty0")
        near = sent.join(home.select("*", at("px", side).alias("tx"), at("py", side).alias("ty")), ["tx", "ty"]).withColumn("d2", d2).where(F.col("d2") <= side * side)
        found = keep(near.groupBy("x", "y").agg(F.min_by("point_id", F.struct("d2", "point_id")).alias("point_id")))
        out = found if out is None else out.unionByName(found)
        if side >= most:
            break
        side = min(side * 2, most)
        left = keep(left.join(found, ["x", "y"], "left_anti"))
        if left.isEmpty():
            break
    return asking.join(out, ["x", "y"]).select("session_id", "sample_id", "point_id")


def update_actions(vector: DataFrame | None, actions: DataFrame, points: DataFrame, facets: DataFrame, weights: dict[str, float], how: str = "share", tile: float | None = None, reach: float | None = None, domain: DataFrame | None = None) -> DataFrame:
    """Explicit feedback: each action adds its weight to the facets of the nearest point; actions with weight 0 or less are left out."""
    told = {k: v for k, v in weights.items() if v > 0}
    w = F.create_map(*[F.lit(x) for kv in told.items() for x in kv])
    chosen = actions.where(F.col("modality").isin(list(told)))
    near = nearest_points(chosen, points, tile, reach).join(chosen.select("session_id", "sample_id", w[F.col("modality")].cast("double").alias("add")), ["session_id", "sample_id"])
    add = near.groupBy("session_id", "point_id").agg(F.sum("add").alias("add")).join(facets.hint("merge"), "point_id").groupBy("session_id", "attr", "val").agg(F.sum("add").alias("add"))
    if how == "softmax" and domain is None:
        domain = facets.select("attr", "val").distinct()
    return _added(vector, add, how, domain)


def irrelevant_cells(vector: DataFrame) -> DataFrame:
    return vector.where("weight = 0")


def weak_cells(vector: DataFrame, threshold: float) -> DataFrame:
    return vector.where((F.col("weight") > 0) & (F.col("weight") < threshold))


def top_facets(vector: DataFrame, n: int = 1, by_attribute: bool = False) -> DataFrame:
    keys = ["session_id", "attr"] if by_attribute else ["session_id"]
    w = Window.partitionBy(*keys).orderBy(F.round("weight", 12).desc(), "attr", "val")
    return vector.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)


def signatures(points: DataFrame, spec: list[Facet]) -> DataFrame:
    """(sig, facets, n): distinct facet combinations; there are far fewer than points."""
    return points.select(signature(spec).alias("facets")).groupBy("facets").agg(F.count("*").alias("n")).withColumn("sig", signature_name(F.col("facets")))


def signature_name(facets: Column) -> Column:
    return F.concat_ws("|", F.transform(facets, lambda f: F.concat_ws("=", f["attr"], f["val"])))


def signature_similarity(sigs: DataFrame, vector: DataFrame, kinds: dict[str, str] | None = None, default: str = "share_of_max", missing: str = "skip", attributes: int | None = None) -> DataFrame:
    """(session_id, sig, sim) of all signatures to all vectors: signatures x sessions, never points x sessions."""
    w = Window.partitionBy("session_id", "attr")
    told = vector.withColumns({"top": F.max("weight").over(w), "norm": F.sqrt(F.sum(F.col("weight") * F.col("weight")).over(w)), "touched": F.sum((F.col("weight") > 0).cast("int")).over(w)})
    slices = told.select("session_id", "attr", "top", "norm", "touched").distinct()
    cells = sigs.select("sig", F.explode("facets").alias("f")).select("sig", "f.*")
    met = cells.join(slices, "attr").join(told.select("session_id", "attr", "val", "weight"), ["session_id", "attr", "val"], "left").withColumn("weight", F.coalesce("weight", F.lit(0.0)))
    score = SIM[default](F.col("weight"), F.col("top"), F.col("norm"), F.col("touched"))
    for attr, kind in (kinds or {}).items():
        score = F.when(F.col("attr") == attr, SIM[kind](F.col("weight"), F.col("top"), F.col("norm"), F.col("touched"))).otherwise(score)
    by_attr = met.withColumn("s", score).groupBy("session_id", "sig", "attr").agg(F.avg("s").alias("s"))
    mean = F.sum("s") / F.lit(float(attributes)) if missing == "zero" and attributes else F.avg("s")
    return by_attr.groupBy("session_id", "sig").agg(F.round(mean, 12).alias("sim"))


def similarity_to_vector(points: DataFrame, vector: DataFrame, spec: list[Facet], **how) -> DataFrame:
    """(session_id, point_id, sim) for one or few sessions; for many use ``signature_similarity``."""
    scored = signature_similarity(signatures(points, spec), vector, **how)
    return points.select("point_id", signature_name(signature(spec)).alias("sig")).join(scored, "sig").select("session_id", "point_id", "sim")


def profile(found: DataFrame, points: DataFrame, also: list[Attribute]) -> DataFrame:
    """(session_id, expected_<attr>, ...): what the matched points of a session have on average, by attribute."""
    met = found.select("session_id", "point_id").distinct().join(points.select("point_id", *dict.fromkeys(a.column for a in also)), "point_id")
    out = met.select("session_id").distinct()
    for a in also:
        out = out.join(a.expected(met).withColumnRenamed("session_id", "of"), F.col("session_id") == F.col("of"), "left").drop("of")
    return out


def mixed_similarity(points: DataFrame, vector: DataFrame, found: DataFrame, spec: list[Facet], also: list[Attribute], most: int = 10_000, **how) -> DataFrame:
    """(session_id, point_id, sim): the mean over facet attributes (against the vector) and further attributes (against the profile).

    Sessions are the queries of a scan over all points; they travel, so their number is
    checked against ``most``.
    """
    asked = profile(found, points, also)
    if asked.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} sessions at once")
    scored = signature_similarity(signatures(points, spec), vector, **how).withColumnRenamed("sim", "facet_sim")
    named = points.select("point_id", signature(spec).alias("facets"), *dict.fromkeys(a.column for a in also)).withColumn("sig", signature_name(F.col("facets")))
    met = named.join(F.broadcast(asked)).join(scored, ["session_id", "sig"])
    parts = [F.col("facet_sim") * F.size(F.array_distinct(F.transform("facets", lambda f: f["attr"]))), *[a.similarity(F.col(a.column), F.col(f"expected_{a.attr}")) for a in also]]
    known = [F.size(F.array_distinct(F.transform("facets", lambda f: f["attr"]))), *[a.known(F.col(a.column), F.col(f"expected_{a.attr}")).cast("int") for a in also]]
    total, number = sum((F.coalesce(p, F.lit(0.0)) for p in parts), F.lit(0.0)), sum(known, F.lit(0))
    return met.select("session_id", "point_id", F.round(F.coalesce(F.try_divide(total, number), F.lit(0.0)), 12).alias("sim"))


def preference_drift(log: DataFrame, grain: str = "month") -> DataFrame:
    """Change of each cell's mean weight from one period to the next; ``log`` has ``at`` (timestamp)."""
    mean = log.groupBy("session_id", "attr", "val", F.date_trunc(grain, "at").alias("period")).agg(F.avg("weight").alias("weight"))
    w = Window.partitionBy("session_id", "attr", "val").orderBy("period")
    return mean.withColumn("change", F.col("weight") - F.lag("weight").over(w))
