"""An adaptive quadtree over stored points: Morton keys, counts per prefix, leaves.

A cell is its Morton prefix with a leading 1 bit, so cells of all depths have distinct
numbers. A leaf is the shallowest cell with at most ``capacity`` points whose parent holds
more; points on a split line belong to the upper or right cell. Cells at the rim of
``bounds`` reach to infinity, so points and zones outside meet there and nothing is lost;
bounds are those of the data unless others are given. A point without a place is in no cell.

Zones meet cells by equality of keys: a zone's box is covered by at most four cells of about
its own size, and a leaf meets a cover cell if one is a prefix of the other. The directory
(about n / capacity rows) is a table like any other, so no side has to fit in memory. A leaf
that can't be split further and holds more than ``hot`` points is dealt out by the points' ids.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Bounds = tuple[float, float, float, float]
INF = float("inf")
#: A zone that comes so near to a cell touches it; corners of overlaps are rounded.
TOUCH = 5e-8
#: Points of a leaf beyond which its join is dealt out over several tasks.
HOT = 100_000


def data_bounds(points: DataFrame, x: str = "x", y: str = "y") -> Bounds:
    """The box of all places; (0, 0, 1, 1) without any."""
    r = points.where(placed(x, y)).agg(*[f(c) for f in (F.min, F.max) for c in (x, y)]).first()
    if r[0] is None:
        return 0.0, 0.0, 1.0, 1.0
    return float(r[0]), float(r[1]), max(float(r[2]), float(r[0]) + 1e-9), max(float(r[3]), float(r[1]) + 1e-9)


def placed(x: str = "x", y: str = "y") -> Column:
    return F.col(x).isNotNull() & F.col(y).isNotNull() & ~F.isnan(F.col(x).cast("double")) & ~F.isnan(F.col(y).cast("double"))


def morton(x: Column, y: Column, bounds: Bounds, depth: int) -> Column:
    """Interleaved bits of the cell at ``depth``, with the leading 1."""
    x0, y0, x1, y1 = bounds
    side = 1 << depth

    def spot(v: Column, low: float, high: float) -> Column:
        return F.greatest(F.lit(0), F.least(F.lit(side - 1), F.floor((v - low) * side / (high - low)))).cast("long")

    def spread(v: Column) -> Column:
        out = F.lit(0).cast("long")
        for k in range(depth):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(v, k).bitwiseAND(F.lit(1).cast("long")), 2 * k))
        return out

    return spread(spot(x, x0, x1)).bitwiseOR(F.shiftleft(spread(spot(y, y0, y1)), 1)).bitwiseOR(F.lit(1 << 2 * depth).cast("long"))


def with_morton(points: DataFrame, bounds: Bounds, depth: int, x: str = "x", y: str = "y") -> DataFrame:
    return points.withColumn("morton", morton(F.col(x), F.col(y), bounds, depth))


def leaf_directory(keyed: DataFrame, capacity: int, max_depth: int) -> DataFrame:
    """(cell, depth, n) of all leaves that hold points: one count per key, then roll-ups of those."""
    fine = keyed.groupBy("morton").agg(F.count("*").alias("n"))
    levels = fine.select("n", F.explode(F.transform(F.sequence(F.lit(0), F.lit(max_depth)), lambda d: F.struct(d.alias("depth"), F.expr("0L").alias("z")))).alias("s"), "morton")
    cells = levels.select(F.col("s.depth").alias("depth"), F.expr(f"shiftright(morton, 2 * ({max_depth} - s.depth))").alias("cell"), "n").groupBy("depth", "cell").agg(F.sum("n").alias("n"))
    parents = cells.select((F.col("depth") + 1).alias("depth"), F.col("cell").alias("parent"), F.col("n").alias("above"))
    both = cells.withColumn("parent", F.shiftright("cell", 2)).join(parents, ["depth", "parent"], "left")
    leaf = ((F.col("n") <= capacity) | (F.col("depth") == max_depth)) & (F.col("above").isNull() | (F.col("above") > capacity))
    return both.where(leaf).select("cell", "depth", "n")


def with_bounds(cells: DataFrame, bounds: Bounds) -> DataFrame:
    """Adds the rectangle of each cell; those at the rim are open outwards."""
    x0, y0, x1, y1 = bounds

    def gather(first: int) -> Column:
        bits = F.transform(F.sequence(F.lit(0), F.greatest(F.col("depth") - 1, F.lit(0))), lambda k: F.when(k < F.col("depth"), F.call_function("shiftleft", F.call_function("shiftright", F.col("cell"), 2 * k + first).bitwiseAND(F.lit(1).cast("long")), k)).otherwise(F.lit(0).cast("long")))
        return F.aggregate(bits, F.lit(0).cast("long"), lambda a, b: a + b)

    side = F.pow(F.lit(2.0), F.col("depth"))
    ix, iy = gather(0), gather(1)


    def edge(k: Column, low: float, high: float) -> Column:
        return F.when(k <= 0, F.lit(-INF)).when(k >= side, F.lit(INF)).otherwise(low + (high - low) * k / side)

    box = F.struct(edge(ix, x0, x1).alias("x0"), edge(iy, y0, y1).alias("y0"), edge(ix + 1, x0, x1).alias("x1"), edge(iy + 1, y0, y1).alias("y1"))
    return cells.withColumn("bbox", box)


def with_leaf(keyed: DataFrame, leaves: DataFrame, max_depth: int) -> DataFrame:
    """Adds ``cell`` and ``leaf_n``, its number of points. The directory meets the keys, not the points, by depth-wise prefixes."""
    keys = keyed.select("morton").distinct()
    prefixes = keys.select("morton", F.explode(F.sequence(F.lit(0), F.lit(max_depth))).alias("depth")).withColumn("cell", F.expr(f"shiftright(morton, 2 * ({max_depth} - depth))"))
    of = prefixes.join(leaves.select("cell", F.col("n").alias("leaf_n")), "cell").select("morton", "cell", "leaf_n")
    return keyed.join(of, "morton")


def build_quadtree(points: DataFrame, bounds: Bounds | None = None, capacity: int = 64, max_depth: int = 12, x: str = "x", y: str = "y") -> tuple[DataFrame, DataFrame]:
    """(points that have a place, with morton, cell and leaf_n; cells with depth, n, bbox)."""
    bounds = bounds or data_bounds(points, x, y)
    keyed = with_morton(points.where(placed(x, y)), bounds, max_depth, x, y)
    leaves = leaf_directory(keyed, capacity, max_depth)
    return with_leaf(keyed, leaves, max_depth), with_bounds(leaves, bounds)


def uniform_grid(points: DataFrame, bounds: Bounds | None, depth: int, x: str = "x", y: str = "y") -> tuple[DataFrame, DataFrame]:
    """The variant of one fixed depth: cells are keys."""
    bounds = bounds or data_bounds(points, x, y)
    keyed = with_morton(points.where(placed(x, y)), bounds, depth, x, y).withColumn("cell", F.col("morton"))
    cells = keyed.groupBy("cell").agg(F.count("*").alias("n")).withColumn("depth", F.lit(depth))
    return keyed.join(cells.select("cell", F.col("n").alias("leaf_n")), "cell"), with_bounds(cells.select("cell", "depth", "n"), bounds)


def zone_covers(zones: DataFrame, bounds: Bounds, max_depth: int) -> DataFrame:
    """Adds cover: the cells (at most four) of about the zone's size that hold its box."""
    x0, y0, x1, y1 = bounds
    box = F.col("zone_box")
    share = F.greatest((box["x1"] - box["x0"]) / (x1 - x0), (box["y1"] - box["y0"]) / (y1 - y0))
    depth = F.least(F.lit(max_depth), F.greatest(F.lit(0), F.floor(-F.log2(F.greatest(share, F.lit(1e-12)))))).cast("int")
    corners = [morton(box[a], box[b], bounds, max_depth) for a in ("x0", "x1") for b in ("y0", "y1")]
    deep = zones.withColumns({"cover_depth": depth, "corner": F.explode(F.array(*corners))})
    return deep.withColumn("cover", F.expr(f"shiftright(corner, 2 * ({max_depth} - cover_depth))")).drop("corner").dropDuplicates(["session_id", "zone_id", "cover"])


def cells_for_zones(cells: DataFrame, zones: DataFrame, bounds: Bounds, max_depth: int = 10) -> DataFrame:
    """(session_id, zone_id, cell, n, full): cells that meet a zone, touching included. Keys first, then boxes, then the zone's edges (separating axes)."""
    a, b = F.col("bbox"), F.col("zone_box")
    wide = F.struct((a["x0"] - TOUCH).alias("x0"), (a["y0"] - TOUCH).alias("y0"), (a["x1"] + TOUCH).alias("x1"), (a["y1"] + TOUCH).alias("y1"))
    asked = zone_covers(zones.select("session_id", "zone_id", "edges", wide.alias("zone_box")), bounds, max_depth)
    up = F.expr("transform(sequence(0, depth), k -> shiftright(cell, 2 * k))")
    below = cells.withColumn("cover", F.explode(up)).join(asked, "cover")
    above = asked.where("cover_depth > 0").withColumn("cell", F.explode(F.expr("transform(sequence(1, cover_depth), k -> shiftright(cover, 2 * k))")))
    above = above.dropDuplicates(["session_id", "zone_id", "cell"]).join(cells, "cell")
    shape = ["session_id", "zone_id", "edges", "zone_box", "cell", "n", "bbox"]
    met = below.select(shape).unionByName(above.select(shape)).where((a["x0"] <= b["x1"]) & (b["x0"] <= a["x1"]) & (a["y0"] <= b["y1"]) & (b["y0"] <= a["y1"]))

    def best(e: Column, inner: bool) -> Column:
        """The largest (or smallest) signed side of the four corners; what is open is cut where the zone ends."""
        x = {"x0": F.greatest(a["x0"], b["x0"] - 1), "x1": F.least(a["x1"], b["x1"] + 1)}
        y = {"y0": F.greatest(a["y0"], b["y0"] - 1), "y1": F.least(a["y1"], b["y1"] + 1)}
        sides = [e["dx"] * (v - e["y"]) - e["dy"] * (u - e["x"]) for u in x.values() for v in y.values()]
        return F.least(*sides) if inner else F.greatest(*sides)

    kept = met.where(F.forall("edges", lambda e: best(e, False) >= -1e-9))
    return kept.select("session_id", "zone_id", "cell", "n", F.forall("edges", lambda e: best(e, True) > 1e-9).alias("full"))


def points_in_cells(keyed: DataFrame, hit: DataFrame, hot: int = HOT) -> DataFrame:
    """Joins points to the cells that zones meet; a leaf of more than ``hot`` points goes to several tasks."""
    parts = F.ceil(F.col("leaf_n") / hot).cast("int")
    a = keyed.withColumn("part", F.pmod(F.xxhash64("point_id"), parts).cast("int"))
    b = hit.withColumn("part", F.explode(F.sequence(F.lit(0), (F.ceil(F.col("n") / hot) - 1).cast("int")))).drop("n")
    return a.join(b, ["cell", "part"]).drop("part")
