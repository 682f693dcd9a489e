"""Highlights: neighbour lists, the anchor, and the greedy search for spread."""

from __future__ import annotations

import time
from collections.abc import Callable
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import diversity_np, geo_distance_np
from ..functions.similarity import Attribute, shared_facets
from ..keep import keep
from .feedback import Facet, signature, signature_name, signature_similarity, signatures

#: Candidates whose distances are taken at once.
BLOCK = 512
#: Stands for the signature of no point in particular.
NO_SIGNATURE = "\0"
#: Rows of a list that are read first where no budget says how many a search can use.
DEPTH = 4096
#: Full lists are quadratic; refuse them beyond so many points.
MAX_FULL = 20_000
MAX_EXHAUSTIVE = 25
#: Rows and owners of a tile of vectors, and its distances that are in memory at once.
TILE_ROWS, TILE_OWNERS, TILE_CELLS = 16384, 16384, 1 << 21
#: Rows of a lane, of which the smallest distance is taken first.
LANE = 64
SEARCH = "session_id long, slot int, point_id long, list_rank int, sim double, scans int, swaps int, diversity_before double, diversity_km double"


def candidates(points: DataFrame, found: DataFrame, search: str = "unseen") -> DataFrame:
    """Points an analyst hasn't met yet (``unseen``) or all."""
    if search == "all":
        return points
    return points.join(found.select("point_id").distinct(), "point_id", "left_anti")


def signature_lists(rows: DataFrame, asked: DataFrame, most: int) -> DataFrame:
    """(my_sig, r, point_id, ..., sim): the first ``most`` points by similarity, then id, for each signature (my_sig, mine) asked.

    ``rows`` carry point_id, facets and sig. Signatures that share a facet meet on it; levels
    of similarity are taken until they hold ``most`` points, and of a signature only its first
    ``most`` points go on, so neither points nor all pairs of signatures meet the asked ones.
    """
    kinds = rows.groupBy("sig").agg(F.first("facets").alias("facets"), F.count("*").alias("n"))
    mine = asked.select("my_sig", F.size("mine").alias("my_size"), F.explode("mine").alias("f"))
    theirs = kinds.select("sig", "n", F.size("facets").alias("size"), F.explode("facets").alias("f"))
    met = mine.join(theirs, "f").groupBy("my_sig", "sig").agg(F.count("*").alias("both"), F.first("my_size").alias("my_size"), F.first("size").alias("size"), F.first("n").alias("n"))
    sims = met.select("my_sig", "sig", "n", F.round(F.col("both") / F.greatest("my_size", "size"), 12).alias("sim"))
    held = asked.select("my_sig").join(sims.groupBy("my_sig").agg(F.sum("n").alias("held")), "my_sig", "left")
    short = held.where(F.coalesce("held", F.lit(0)) < most).select("my_sig")  # these go on with what shares nothing
    none = short.join(kinds.select("sig", "n")).join(sims.select("my_sig", "sig"), ["my_sig", "sig"], "left_anti").select("my_sig", "sig", "n", F.lit(0.0).alias("sim"))
    sims = sims.unionByName(none)
    level = Window.partitionBy("my_sig").orderBy(F.col("sim").desc())
    sims = sims.withColumn("before", F.sum("n").over(level) - F.sum("n").over(Window.partitionBy("my_sig", "sim"))).where(F.col("before") < most)
    few = rows.drop("facets").withColumn("in_sig", F.row_number().over(Window.partitionBy("sig").orderBy("point_id"))).where(F.col("in_sig") <= most)
    lists = sims.select("my_sig", "sig", "sim").join(few, "sig").drop("sig", "in_sig")
    return lists.withColumn("r", F.row_number().over(Window.partitionBy("my_sig").orderBy(F.col("sim").desc(), "point_id"))).where(F.col("r") <= most)


def build_neighbours(points: DataFrame, spec: list[Facet], strategy: str = "signature", depth: int | None = None) -> DataFrame:
    """Similarity-ordered lists of all points: (owner, rank, point_id, sim).

    full: all pairs of points; with a ``depth`` and more than MAX_FULL points, pairs of facet
    combinations stand for those of their points. signature: one list per facet combination,
    cut at ``depth`` and handed to its points; equal results. Without ``depth`` every point is
    in every list, so small tables only.
    """
    rows = points.select("point_id", signature(spec).alias("facets"))
    order = Window.partitionBy("owner").orderBy(F.col("sim").desc(), "point_id")
    if (strategy == "full" or depth is None) and points.limit(MAX_FULL + 1).count() > MAX_FULL:
        if depth is None:
            raise ValueError(f"full lists of more than {MAX_FULL} points; give a depth")
        strategy = "signature" if strategy == "full" else strategy
    if strategy == "full":
        a, b = rows.toDF("owner", "facets_a"), rows.toDF("point_id", "facets_b")
        pairs = a.join(b, F.col("owner") != F.col("point_id")).select("owner", "point_id", F.round(shared_facets(F.col("facets_a"), F.col("facets_b")), 12).alias("sim"))
    elif strategy == "signature":
        named = rows.withColumn("sig", signature_name(F.col("facets")))
        asked = named.groupBy(F.col("sig").alias("my_sig")).agg(F.first("facets").alias("mine"))
        lists = signature_lists(named, asked, (depth or MAX_FULL) + 1)
        pairs = named.select(F.col("point_id").alias("owner"), F.col("sig").alias("my_sig")).join(lists, "my_sig").where("owner <> point_id").select("owner", "point_id", "sim")
    else:
        raise ValueError(f"unknown strategy {strategy!r}")
    lists = pairs.withColumn("rank", F.row_number().over(order))
    return (lists.where(F.col("rank") <= depth) if depth else lists).select("owner", "rank", "point_id", "sim")


def list_on_demand(points: DataFrame, spec: list[Facet], owners: DataFrame | int, depth: int = DEPTH, unseen: DataFrame | None = None, also: list[Attribute] | None = None, most: int = 10_000) -> DataFrame:
    """(owner, rank, point_id, lat, lon, sim): the lists of some points, by one scan over all. ``unseen`` drops matched points before the cut.

    Owners (a table with point_id, or one id) are the queries; they travel, so their number is
    checked against ``most``. Similarity is the mean over facets and further attributes.
    """
    more = list(dict.fromkeys(a.column for a in also or []))
    rows = points if unseen is None else points.join(unseen.select("point_id").distinct(), "point_id", "left_anti")
    wanted = points.where(F.col("point_id") == owners) if isinstance(owners, int) else points.join(owners.select("point_id").distinct(), "point_id", "left_semi")
    mine = wanted.select(F.col("point_id").alias("owner"), signature(spec).alias("mine"), *[F.col(c).alias(f"my_{c}") for c in more])
    if mine.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} owners at once")
    met = rows.select("point_id", "lat", "lon", signature(spec).alias("facets"), *more).join(F.broadcast(mine), F.col("owner") != F.col("point_id"))
    sim = shared_facets(F.col("mine"), F.col("facets"))
    if also:
        n = F.greatest(F.size("mine"), F.size("facets"))
        total, number = sim * n, n
        for a in also:
            total = total + F.coalesce(a.similarity(F.col(f"my_{a.column}"), F.col(a.column)), F.lit(0.0))
            number = number + a.known(F.col(f"my_{a.column}"), F.col(a.column)).cast("int")
        sim = F.coalesce(F.try_divide(total, number), F.lit(0.0))
    scored = met.select("owner", "point_id", "lat", "lon", F.round(sim, 12).alias("sim"))
    rank = F.row_number().over(Window.partitionBy("owner").orderBy(F.col("sim").desc(), "point_id"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= depth).select("owner", "rank", "point_id", "lat", "lon", "sim")


def _vectors(column: pa.ChunkedArray) -> np.ndarray:
    """A matrix of equally long vectors; others are refused."""
    flat = pa.concat_arrays(column.chunks)
    if len(np.unique(np.diff(flat.offsets.to_numpy()))) > 1:
        raise ValueError("vectors of different lengths")
    return flat.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(flat), -1)


def _measured(owners: np.ndarray, a: np.ndarray, ids: np.ndarray, b: np.ndarray, mine: np.ndarray, theirs: np.ndarray, depth: int) -> list[tuple]:
    """``nearest_in_tile`` with buckets of all pairs compared."""
    square = (b * b).sum(axis=1)
    stripe, out = max(1, TILE_CELLS // len(b)), []
    for at in range(0, len(a), stripe):
        part = a[at : at + stripe]
        near = (part * part).sum(axis=1)[:, None] + square - 2 * (part @ b.T)
        slack = 1e-9 * (1 + (part * part).sum(axis=1) + square.max())  # products are rounded, so what comes close is measured again
        other = owners[at : at + stripe, None] != ids
        shared = np.zeros(near.shape, bool)
        for t in range(mine.shape[1]):
            shared |= mine[at : at + stripe, t, None] == theirs[:, t]
        shared &= other
        enough = shared.sum(axis=1) >= depth
        near[np.where(enough[:, None], ~shared, ~other)] = np.inf
        k = min(depth, len(b)) - 1
        most = np.partition(near, k, axis=1)[:, k] + slack
        for i, (row, limit) in enumerate(zip(near, most, strict=True)):
            hit = np.flatnonzero((row <= limit) & np.isfinite(row))
            if not enough[i]:
                hit = np.union1d(hit, np.flatnonzero(shared[i]))
            far = np.sqrt(((b[hit] - part[i]) ** 2).sum(axis=1))
            met = shared[i][hit]
            first = np.lexsort((ids[hit], np.round(far, 12)))
            if enough[i]:
                first = first[:depth]
            else:
                first = first[(np.arange(len(first)) < depth) | met[first]]
            out.append((np.full(len(first), owners[at + i]), ids[hit[first]], far[first], met[first]))
    return out


def _screened(owners: np.ndarray, a: np.ndarray, ids: np.ndarray, b: np.ndarray, mine: np.ndarray, theirs: np.ndarray, depth: int) -> tuple[list[tuple], np.ndarray]:
    """(lists, which owners have none yet): buckets are compared only for the rows nearest by rounded products.

    Rows are dealt into lanes. All rows nearer than ``bound``, the largest of an owner's
    smallest lane minima, lie in those lanes; if ``depth`` of them share a bucket and are
    nearer than ``bound`` by more than rounding, no other row can be in the list.
    """
    kind = np.float32 if max(np.abs(a).max(), np.abs(b).max()) < 1e15 else float
    lanes, few = -(-len(b) // LANE), 2 * depth + 4
    todo = np.ones(len(a), bool)
    if lanes <= few:
        return [], todo
    square, own = (b * b).sum(axis=1), (a * a).sum(axis=1)
    rows = np.zeros((lanes * LANE, b.shape[1] + 1), kind)
    rows[: len(b), :-1], rows[: len(b), -1], rows[len(b) :, -1] = b, square, np.inf
    asked = np.c_[-2 * a, np.ones(len(a))].astype(kind)
    slack = 4 * (b.shape[1] + 3) * np.finfo(kind).eps * (own + square.max())
    stripe, out = max(1, TILE_CELLS // len(rows)), []
    for at in range(0, len(a), stripe):
        near = asked[at : at + stripe] @ rows.T  # less the owner's square
        low = near.reshape(len(near), LANE, lanes).min(axis=1)
        lane = np.argpartition(low, few - 1, axis=1)[:, :few]
        bound = np.take_along_axis(low, lane, axis=1).max(axis=1)
        place = (lane[:, None, :] + lanes * np.arange(LANE)[:, None]).reshape(len(near), -1)
        i, j = np.nonzero(np.take_along_axis(near, place, axis=1) <= bound[:, None])
        j = place[i, j]
        i, j = i[j < len(b)] + at, j[j < len(b)]
        met = (owners[i] != ids[j]) & (mine[i] == theirs[j]).any(axis=1)
        i, j = i[met], j[met]
        far = np.sqrt(((b[j] - a[i]) ** 2).sum(axis=1))
        order = np.lexsort((ids[j], np.round(far, 12), i))
        i, j, far = i[order], j[order], far[order]
        rank = np.arange(len(i)) - np.searchsorted(i, i)
        sure = (far + 1e-11) ** 2 < bound[i - at].astype(float) + own[i] - slack[i]
        todo[i[(rank == depth - 1) & sure]] = False
        keep = (rank < depth) & ~todo[i]
        out.append((owners[i[keep]], ids[j[keep]], far[keep], np.ones(int(keep.sum()), bool)))
    return out, todo


def nearest_in_tile(owners: np.ndarray, a: np.ndarray, ids: np.ndarray, b: np.ndarray, directions: np.ndarray, bucket: float, depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(owner, point_id, distance, met) for the vectors ``a`` of owners and ``b`` of rows: the ``depth`` nearest rows that share a bucket with an owner, or, where fewer do, those and the nearest of all. Vectors that aren't finite are in no list and have none."""
    here, there = (np.isfinite(v).all(axis=1) for v in (a, b))
    owners, a, ids, b = owners[here], a[here], ids[there], b[there]
    out = [(owners[:0], ids[:0], np.zeros(0), np.zeros(0, bool))]
    if len(a) and len(b):
        # of equal vectors only the first by id can be in a list
        same = np.unique((b + 0.0).view(np.dtype((np.void, b.shape[1] * 8))).ravel(), return_inverse=True)[1]
        order = np.lexsort((ids, same))
        rank = np.arange(len(order)) - np.searchsorted(same[order], same[order])
        order = order[rank < depth + np.unique(ids, return_counts=True)[1].max()]
        ids, b = ids[order], b[order]
        mine, theirs = (np.floor(v @ directions / bucket) for v in (a, b))
        quick, todo = _screened(owners, a, ids, b, mine, theirs, depth)
        out += quick + _measured(owners[todo], a[todo], ids, b, mine[todo], theirs, depth)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def approximate_lists(points: DataFrame, column: str, owners: DataFrame | None = None, tables: int = 10, bucket: float = 1.2, depth: int = 20) -> DataFrame:
    """Lists of vectors by random projections: (owner, rank, point_id, sim = -distance).

    Every row is indexed; owners (default: all points) ask. An owner that meets fewer than
    ``depth`` rows in its buckets is compared with all rows instead. Recall grows with
    ``tables`` and ``bucket``; it is measured by ``measures.list_recall``.

    Owners and rows meet in tiles of bounded size, in which a pair is told once by its
    buckets in all tables and measured by a product of matrices; a tile hands on ``depth``
    rows an owner. Tiles grow with owners x rows. A point without a vector has no list.
    """
    e = F.col(column) if points.schema[column].dataType.simpleString() == "array<float>" else F.col(column).cast("array<double>")
    rows = points.where(F.col(column).isNotNull()).select("point_id", e.alias("e"))
    asked = rows if owners is None else rows.join(owners.select("point_id").distinct(), "point_id", "left_semi")
    first = rows.select(F.size("e").alias("n")).first()
    directions = np.random.default_rng(7).normal(size=(first.n if first else 1, tables))
    directions /= np.linalg.norm(directions, axis=0)
    groups, parts = (max(1, -(-df.count() // size)) for df, size in ((rows, TILE_ROWS), (asked, TILE_OWNERS)))

    def dealt(df: DataFrame, own: str, n: int, other: str, m: int) -> DataFrame:
        home = df.select(F.col("point_id").alias(f"{own}_id"), F.col("e").alias(f"{own}_e"), F.pmod(F.xxhash64("point_id"), F.lit(n)).cast("int").alias(own))
        return home.withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(m - 1)))).groupBy("o", "g")

    def tile(left: pa.Table, right: pa.Table) -> pa.Table:
        if not (left.num_rows and right.num_rows):
            return told.empty_table()
        found = nearest_in_tile(left["o_id"].to_numpy(), _vectors(left["o_e"]), right["g_id"].to_numpy(), _vectors(right["g_e"]), directions, bucket, depth)
        return pa.table(dict(zip(told.names, found, strict=True)), schema=told)

    told = pa.schema([("owner", pa.int64()), ("point_id", pa.int64()), ("far", pa.float64()), ("met", pa.bool_())])
    near = dealt(asked, "o", parts, "g", groups).cogroup(dealt(rows, "g", groups, "o", parts)).applyInArrow(tile, "owner long, point_id long, far double, met boolean")
    few = F.count(F.when(F.col("met"), 1)).over(Window.partitionBy("owner")) < depth
    near = near.select("owner", "point_id", (-F.col("far")).alias("sim"), "met", few.alias("few")).where("met or few")
    w = Window.partitionBy("owner").orderBy(F.round("sim", 12).desc(), "point_id")
    return near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= depth).select("owner", "rank", "point_id", "sim")


class ListCursor:
    """Sequential access to an ordered list, a partition at a time."""

    def __init__(self, lists: DataFrame) -> None:
        self._rows = lists.orderBy("rank").toLocalIterator()

    def next(self):
        return next(self._rows, None)


def _first_unseen(named: DataFrame, seen: DataFrame) -> DataFrame:
    """(session_id, sig, point_id): the smallest unseen point of each signature a session has met; none if all were met.

    A signature's points are numbered by id, but only as many as one session has met of one,
    and one more; the first number a session lacks is its answer.
    """
    most = seen.groupBy("session_id", "sig").agg(F.count("*").alias("n")).agg(F.coalesce(F.max("n"), F.lit(0))).first()[0] + 1
    ranked = named.withColumn("r", F.row_number().over(Window.partitionBy("sig").orderBy("point_id"))).where(F.col("r") <= most)
    met = seen.join(ranked.select("point_id", "sig", "r"), ["point_id", "sig"], "left")
    met = met.withColumn("k", F.row_number().over(Window.partitionBy("session_id", "sig").orderBy(F.col("r").asc_nulls_last())))
    gap = met.groupBy("session_id", "sig").agg(F.coalesce(F.min(F.when(F.col("r").isNull() | (F.col("r") > F.col("k")), F.col("k"))), F.count("*") + 1).alias("r"))
    return gap.join(ranked, ["sig", "r"]).select("session_id", "sig", "point_id")


def anchors(points: DataFrame, vector: DataFrame, spec: list[Facet], found: DataFrame | None = None, sessions: DataFrame | None = None, **how) -> DataFrame:
    """(session_id, anchor, sim_f): the unseen point most similar to each session's vector; ties by id.

    A session of ``sessions`` without a vector finds all points equally dissimilar, so it
    starts from its smallest unseen id. Signatures are scored against vectors; points meet
    sessions only where matched.
    """
    named = points.select("point_id", signature_name(signature(spec)).alias("sig"))
    scored = signature_similarity(signatures(points, spec), vector, **how)
    if sessions is not None:
        blank = sessions.select("session_id").distinct().join(vector.select("session_id").distinct(), "session_id", "left_anti")
        named = named.unionByName(points.select("point_id", F.lit(NO_SIGNATURE).alias("sig")))
        scored = scored.unionByName(blank.select("session_id", F.lit(NO_SIGNATURE).alias("sig"), F.lit(0.0).alias("sim")))
    ids = named.groupBy("sig").agg(F.min("point_id").alias("first"))
    best = scored.join(ids, "sig")
    if found is None:
        best = best.withColumn("point_id", F.col("first"))
    else:
        seen = keep(found.select("session_id", "point_id").distinct().join(named, "point_id").join(scored.select("session_id", "sig"), ["session_id", "sig"], "left_semi"))
        touched = seen.select("session_id", "sig").distinct().withColumn("touched", F.lit(True))
        left = _first_unseen(named, seen).withColumnRenamed("point_id", "unseen")
        best = best.join(touched, ["session_id", "sig"], "left").join(left, ["session_id", "sig"], "left").withColumn("point_id", F.when(F.col("touched"), F.col("unseen")).otherwise(F.col("first"))).where("point_id is not null")
    return best.groupBy("session_id").agg(F.max_by(F.struct("point_id", "sim"), F.struct("sim", -F.col("point_id"))).alias("b")).select("session_id", F.col("b.point_id").alias("anchor"), F.col("b.sim").alias("sim_f"))


def list_prefix(points: DataFrame, spec: list[Facet], starts: DataFrame, depth: int | None = None, found: DataFrame | None = None, include_anchor: bool = False) -> DataFrame:
    """(session_id, rank, point_id, lat, lon, sim): the first ``depth`` unseen rows of each anchor's list (None: all).

    Lists are taken per distinct anchor signature; a session's matched points are filtered
    after reading ``depth`` plus the most that one session has matched.
    """
    rows = points.select("point_id", "lat", "lon", signature(spec).alias("facets")).withColumn("sig", signature_name(F.col("facets")))
    mine = starts.join(rows.select(F.col("point_id").alias("anchor"), F.col("facets").alias("mine"), F.col("sig").alias("my_sig")), "anchor").select("session_id", "anchor", "mine", "my_sig")
    seen = None if found is None else found.select("session_id", "point_id").distinct()
    if depth is None:
        most = points.count() + 1
    else:
        most = depth + 1 + (0 if seen is None else seen.join(mine.select("session_id"), "session_id", "left_semi").groupBy("session_id").count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0])
    lists = mine.select("session_id", "anchor", "my_sig").join(signature_lists(rows, mine.select("my_sig", "mine").dropDuplicates(["my_sig"]), most), "my_sig")
    if not include_anchor:
        lists = lists.where("point_id <> anchor")
    if seen is not None:
        lists = lists.join(seen, ["session_id", "point_id"], "left_anti")
    rank = F.row_number().over(Window.partitionBy("session_id").orderBy(F.col("sim").desc(), "point_id"))
    lists = lists.withColumn("rank", rank)
    return (lists if depth is None else lists.where(F.col("rank") <= depth)).select("session_id", "rank", "point_id", "lat", "lon", "sim")


def greedy(lat: np.ndarray, lon: np.ndarray, k: int, max_scans: int | None = None, time_limit_ms: float | None = None, swap: str = "first", metric: str = "haversine", sim: np.ndarray | None = None, min_sim: float | None = None, patience: int | None = None, watch: Callable[[int, np.ndarray], None] | None = None) -> tuple[list[int], int, int]:
    """(positions chosen, scans, swaps).

    Candidates are scanned in order, a block of distances at a time; between two swaps the
    chosen set stands still, so the next one that improves it is found at once. ``watch`` is
    told the scans done and the chosen places before each swap and at the end.
    """
    if swap not in ("first", "best", "worst_out"):
        raise ValueError(f"unknown swap rule {swap!r}")
    n, at = len(lat), np.arange(min(k, len(lat)))
    if len(at) < 2:
        return at.tolist(), 0, 0
    d = geo_distance_np(lat[at][:, None], lon[at][:, None], lat[at][None, :], lon[at][None, :], metric)
    np.fill_diagonal(d, 0.0)
    sums, c, swaps, idle = d.sum(axis=1), k, 0, 0
    end = None if time_limit_ms is None else time.perf_counter() + time_limit_ms / 1000
    stop = n if max_scans is None else min(n, k + max_scans)
    if min_sim is not None and sim is not None:
        low = np.flatnonzero(sim[k:stop] < min_sim)
        stop = k + int(low[0]) if len(low) else stop
    far, base = np.zeros((0, k)), k
    while c < stop and (patience is None or idle < patience) and (end is None or time.perf_counter() < end):
        if c >= base + len(far):
            base = c
            block = slice(base, min(stop, base + BLOCK))
            far = geo_distance_np(lat[block][:, None], lon[block][:, None], lat[at][None, :], lon[at][None, :], metric)
        gain = far[c - base :].sum(axis=1)[:, None] - far[c - base :] - sums
        slots = np.argmin(sums)[None] if swap == "worst_out" else np.arange(k)
        hit = np.flatnonzero((gain[:, slots] > 1e-12).any(axis=1))
        ahead = int(hit[0]) if len(hit) else len(gain)
        if patience is not None and idle + ahead >= patience:
            ahead, hit = patience - idle, hit[:0]
        c, idle = c + ahead, idle + ahead
        if not len(hit):
            continue
        g = gain[ahead]
        slot = int(slots[0]) if swap == "worst_out" else int(np.argmax(g)) if swap == "best" else int(np.flatnonzero(g > 1e-12)[0])
        if watch is not None:
            watch(c - k, at)
        row = far[c - base].copy()
        row[slot] = 0.0
        sums += row - d[slot]
        sums[slot] = row.sum()
        d[slot], d[:, slot] = row, row
        at[slot], swaps, idle = c, swaps + 1, 0
        c += 1
        rest = slice(c, base + len(far))
        far[c - base :, slot] = geo_distance_np(lat[rest], lon[rest], lat[at[slot]], lon[at[slot]], metric)
    if watch is not None:
        watch(c - k, at)
    return at.tolist(), c - k, swaps


def greedy_highlights(prefix: DataFrame, k: int = 5, time_limit_ms: float | None = 200, max_scans: int | None = None, metric: str = "haversine", swap: str = "first", min_sim: float | None = None, patience: int | None = None) -> DataFrame:
    """k highlights a session from its list prefix, with the log of the search."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rank")
        lat, lon, sim = (pdf[c].to_numpy(float) for c in ("lat", "lon", "sim"))
        at, scans, swaps = greedy(lat, lon, k, max_scans, time_limit_ms, swap, metric, sim, min_sim, patience)
        first = list(range(min(k, len(pdf))))
        return pd.DataFrame({
            "session_id": pdf["session_id"].iloc[0], "slot": range(len(at)), "point_id": pdf["point_id"].to_numpy()[at], "list_rank": pdf["rank"].to_numpy()[at], "sim": sim[at], "scans": scans, "swaps": swaps,
            "diversity_before": diversity_np(lat[first], lon[first], metric), "diversity_km": diversity_np(lat[at], lon[at], metric),
        })

    return prefix.groupBy("session_id").applyInPandas(run, SEARCH)


def search_highlights(points: DataFrame, spec: list[Facet], starts: DataFrame, found: DataFrame | None = None, k: int = 5, time_limit_ms: float | None = 200, max_scans: int | None = None, metric: str = "haversine", swap: str = "first", min_sim: float | None = None, patience: int | None = None, depth: int | None = None) -> DataFrame:
    """k highlights a session, reading as much of its list as the search can use.

    With ``max_scans`` that many rows and k are enough. Else ``depth`` (default DEPTH) rows are
    read; sessions whose search came to the end of what was read, while the list went on, are
    searched again with four times as many, until none is left.
    """
    if max_scans is not None:
        return greedy_highlights(list_prefix(points, spec, starts, max_scans + k, found), k, time_limit_ms, max_scans, metric, swap, min_sim, patience)
    depth, out = max(depth or DEPTH, k + 1), None
    while True:
        rows = keep(greedy_highlights(list_prefix(points, spec, starts, depth, found), k, time_limit_ms, None, metric, swap, min_sim, patience))
        more = rows.where(F.col("scans") + k >= depth).select("session_id").distinct()
        ready = rows.join(more, "session_id", "left_anti")
        out = ready if out is None else out.unionByName(ready)
        if more.isEmpty():
            return out
        starts, depth = starts.join(more, "session_id", "left_semi"), depth * 4


def budget_curve(prefix: DataFrame, ks: list[int], scans: list[int], times_ms: list[float] | None = None, metric: str = "haversine", swap: str = "first") -> DataFrame:
    """(session_id, k, scans, time_ms, diversity_km, diversity_norm, mean_sim) after so many scans, or so much time; scans -1 and time_ms -1: the end of the list, by whose result the norm divides.

    One search to the end of the list gives all points of a curve.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rank")
        lat, lon, sim = (pdf[c].to_numpy(float) for c in ("lat", "lon", "sim"))
        out, session = [], pdf["session_id"].iloc[0]
        for k in ks:
            began, steps = time.perf_counter(), []
            greedy(lat, lon, k, None, None, swap, metric, watch=lambda done, at: steps.append((done, (time.perf_counter() - began) * 1000, at.copy())))  # noqa: B023
            steps = steps or [(0, 0.0, np.arange(min(k, len(pdf))))]
            spread = [diversity_np(lat[at], lon[at], metric) for _, _, at in steps]
            best = spread[-1]
            # a step's set stands until the step's scan; what is chosen after s scans is the first whose end lies at or beyond s
            marks = [(s, -1.0, next((i for i, x in enumerate(steps) if x[0] >= s), len(steps) - 1)) for s in scans] if times_ms is None else [(-1, t, next((i for i, x in enumerate(steps) if x[1] >= t), len(steps) - 1)) for t in times_ms]
            for s, t, i in [*marks, (-1, -1.0, len(steps) - 1)]:
                at = steps[i][2]
                out.append((session, k, s, t, spread[i], spread[i] / best if best > 0 else 0.0, float(sim[at].mean()) if len(at) else 0.0))
        return pd.DataFrame(out, columns=["session_id", "k", "scans", "time_ms", "diversity_km", "diversity_norm", "mean_sim"])

    return prefix.groupBy("session_id").applyInPandas(run, "session_id long, k int, scans int, time_ms double, diversity_km double, diversity_norm double, mean_sim double")


def exhaustive_highlights(prefix: DataFrame, k: int = 3, objective: str = "diversity", alpha: float = 0.5, metric: str = "haversine") -> DataFrame:
    """The best k-set by trying all; at most MAX_EXHAUSTIVE rows a session. objective: diversity, or both (alpha: weight of similarity)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        if len(pdf) > MAX_EXHAUSTIVE:
            raise ValueError(f"{len(pdf)} candidates; at most {MAX_EXHAUSTIVE} can be tried")
        pdf = pdf.sort_values("rank")
        lat, lon, sim, ids = (pdf[c].to_numpy() for c in ("lat", "lon", "sim", "point_id"))
        size = min(k, len(pdf))
        top = max((diversity_np(lat[list(c)], lon[list(c)], metric) for c in combinations(range(len(pdf)), size)), default=0.0) or 1.0
        best = None
        for c in combinations(range(len(pdf)), size):
            d = diversity_np(lat[list(c)], lon[list(c)], metric)
            value = round(d if objective == "diversity" else alpha * float(sim[list(c)].mean()) + (1 - alpha) * d / top, 9)
            key = (-value, sorted(ids[list(c)].tolist()))
            if best is None or key < best[0]:
                best = (key, c, d)
        chosen = sorted(best[1], key=lambda i: ids[i]) if best else []
        return pd.DataFrame({"session_id": pdf["session_id"].iloc[0], "slot": range(len(chosen)), "point_id": ids[chosen], "diversity_km": best[2] if best else 0.0})

    return prefix.groupBy("session_id").applyInPandas(run, "session_id long, slot int, point_id long, diversity_km double")


def flag_highlights(points: DataFrame, chosen: DataFrame) -> DataFrame:
    """All points stay on the map; highlights are marked."""
    return points.join(chosen.select("point_id", F.lit(True).alias("highlight")).distinct(), "point_id", "left").withColumn("highlight", F.coalesce("highlight", F.lit(False)))


def explain_highlights(chosen: DataFrame, facets: DataFrame, vector: DataFrame, n: int = 2) -> DataFrame:
    """The facets of each highlight that weigh most in the session's vector. ``facets`` has several rows a point, which Spark doesn't foresee, so it must not be broadcast."""
    w = Window.partitionBy("session_id", "point_id").orderBy(F.round("weight", 12).desc(), "attr", "val")
    met = chosen.select("session_id", "point_id").join(facets.hint("merge"), "point_id").join(vector, ["session_id", "attr", "val"]).where("weight > 0")
    return met.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n).select("session_id", "point_id", "rank", "attr", "val", "weight")
