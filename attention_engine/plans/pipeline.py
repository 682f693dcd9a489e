"""One iteration of the method, and many."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..keep import keep
from ..operators.feedback import Facet, facet_domain, facetize, update_actions, update_feedback
from ..operators.highlights import anchors, search_highlights
from ..operators.matching import match_points, matched
from ..operators.trace import clip_trace
from ..operators.zones import attention_zones, discover_outlines


@dataclass(frozen=True)
class Params:
    g: int = 3
    eps: float = 20.0
    min_pts: int = 5
    every_ms: int | None = 200
    recurrence: int = 2
    segments: str = "half_open"
    clustering: str = "local"
    delta: float = 1.0
    action_weights: dict = field(default_factory=lambda: {"click": 1.0, "view": 0.5, "purchase": 2.0, "signup": 2.0, "error": 0.0})
    feedback: str = "implicit"
    multiplicity: str = "set"
    normalise: str = "share"
    matching: str = "auto"
    k: int = 5
    depth: int | None = None
    time_limit_ms: float | None = 200
    max_scans: int | None = None
    metric: str = "haversine"
    swap: str = "first"
    min_sim: float | None = None
    patience: int | None = None
    search: str = "unseen"
    since: str | None = None


@dataclass
class State:
    """What lasts from one iteration to the next: the vector, the time up to which it was updated, and with since="last" the points met so far."""

    vector: DataFrame | None = None
    t_last: int = 0
    seen: DataFrame | None = None


def run_iteration(state: State, t_c: int, trace: DataFrame, points: DataFrame, spec: list[Facet], params: Params = Params()) -> tuple[DataFrame, State]:
    """(highlights, next state): k highlights for every session that has a sample by t_c.

    As printed, all samples up to t_c are mined in each iteration. With since="last" only
    those after the last iteration are, and the slices divide the time since then.
    """
    p, vector, facets = params, state.vector, facetize(points, spec)
    t_0 = state.t_last if p.since == "last" and state.t_last else None
    found = None
    domain = facet_domain(points, spec) if p.normalise == "softmax" else None
    if p.feedback in ("implicit", "both"):
        zones = keep(attention_zones(discover_outlines(trace, t_c, p.g, p.eps, p.min_pts, p.every_ms, p.segments, p.clustering, t_0=t_0), p.recurrence))
        met = keep(matched(match_points(points, zones, p.matching), p.multiplicity))
        vector = update_feedback(vector, met, facets, p.delta, p.normalise, domain)
        found = met if state.seen is None or p.since != "last" else keep(state.seen.unionByName(met.select("session_id", "point_id")).distinct())
    if p.feedback in ("explicit", "both"):
        acts = trace.where((F.col("t_ms") <= t_c) & (F.col("t_ms") > (t_0 if t_0 is not None else -1)))
        vector = update_actions(vector, acts, points, facets, p.action_weights, p.normalise, domain=domain)
    vector = keep(vector)
    unseen = found if p.search == "unseen" else None
    starts = keep(anchors(points, vector, spec, unseen, clip_trace(trace, t_c).select("session_id")))
    rows = search_highlights(points, spec, starts, unseen, p.k, p.time_limit_ms, p.max_scans, p.metric, p.swap, p.min_sim, p.patience, p.depth)
    return rows, State(vector, t_c, found.select("session_id", "point_id").distinct() if found is not None else None)


def explore(trace: DataFrame, points: DataFrame, t_cs: list[int], spec: list[Facet], params: Params = Params()) -> tuple[DataFrame, DataFrame]:
    """(highlights, vectors) of several iterations, with ``iter``; each iteration starts from written state."""
    state, chosen, log = State(), None, None
    for i, t_c in enumerate(t_cs):
        rows, state = run_iteration(state, t_c, trace, points, spec, params)
        rows, vector = keep(rows).withColumn("iter", F.lit(i)), state.vector.withColumn("iter", F.lit(i))
        chosen = rows if chosen is None else chosen.unionByName(rows)
        log = vector if log is None else log.unionByName(vector)
    return chosen, log
