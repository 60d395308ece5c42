"""Shared geometry: the dual view, shifted grids, cells met by a ball, sample points, depth of given points.

Everything that touches rows is a column expression; driver code only makes the few numbers of a plan.
"""

from __future__ import annotations

import itertools
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOL = 1e-9
MODULUS = 2**31 - 1


def dims_of(dim: int) -> list[str]:
    return [f"c{i}" for i in range(dim)]


def to_dual(points: DataFrame, radius: float, coords: list[str] | None = None, pos: str | None = None, dim: int = 2, weight: str = "w") -> DataFrame:
    """Balls of radius 1: columns c0.. in place of the coordinates, the rest kept.

    A negative weight in the column ``weight`` fails the job where it is read, without a pass of its own.
    """
    values = [F.col(c) for c in coords] if coords else [F.get(pos, F.lit(i)) for i in range(dim)]
    kept = [F.when(F.col(c) < 0, F.raise_error(F.lit("negative weights: ball methods take none"))).otherwise(F.col(c)).alias(c) if c == weight else F.col(c) for c in points.columns if c not in (coords or [pos])]
    return points.select(*kept, *((v.cast("double") / radius).alias(f"c{i}") for i, v in enumerate(values)))


def shifted_grids(side: float, delta: float, dim: int, mode: str = "thin") -> list[tuple[int, tuple[float, ...]]]:
    """(grid, shift vector): with ``paper`` steps of delta/sqrt(dim) an axis, with ``thin`` half as many, evenly spaced, with ``two`` two, with ``one`` none."""
    per = side * math.sqrt(dim) / delta
    count = {"one": 1, "two": 2}[mode] if mode in ("one", "two") else max(1, math.ceil(round(per if mode == "paper" else per / 2, 9)))
    return list(enumerate(tuple(side * z / count for z in v) for v in itertools.product(range(count), repeat=dim)))


def with_grids(balls: DataFrame, grids: list) -> DataFrame:
    """Every ball once for each grid (g, s0..): an exploded literal, no join."""
    rows = F.array(*(F.struct(F.lit(g).alias("g"), *(F.lit(float(s)).alias(f"s{i}") for i, s in enumerate(shift))) for g, shift in grids))
    return balls.withColumn("grid", F.explode(rows)).select("*", "grid.*").drop("grid")


def ball_cells(balls: DataFrame, grids: list, side: float, dim: int) -> DataFrame:
    """(g, k0.., ball columns): the cells of every grid whose box comes within 1 of the ball's centre."""
    out = with_grids(balls, grids)
    for i in range(dim):
        low = F.floor((F.col(f"c{i}") - F.col(f"s{i}") - 1) / side)
        high = F.floor((F.col(f"c{i}") - F.col(f"s{i}") + 1) / side)
        out = out.withColumn(f"k{i}", F.explode(F.sequence(low.cast("long"), high.cast("long"))))
    gap = sum((F.pow(F.greatest(F.col(f"s{i}") + F.col(f"k{i}") * side - F.col(f"c{i}"), F.lit(0.0), F.col(f"c{i}") - F.col(f"s{i}") - (F.col(f"k{i}") + 1) * side), F.lit(2.0)) for i in range(dim)), F.lit(0.0))
    return out.where(gap <= 1 + TOL)


def with_draws(rows: DataFrame, dim: int, seed) -> DataFrame:
    """``rows`` with ``__h``, a number below the modulus made of seed, grid, cell and sample in plain 64-bit arithmetic.

    Any engine can make it: the seed and the grid, then by axis the square of what is there, so that neighbours differ.
    """
    out = rows.withColumn("__h", F.pmod((seed if isinstance(seed, Column) else F.lit(seed)).cast("long") * 48271 + F.col("g") + 1, F.lit(MODULUS)))
    h = F.col("__h")
    for i in range(dim):
        out = out.withColumn("__h", F.pmod(h * h + 48271 * h + F.col(f"k{i}") + 1_000_003 * (i + 1), F.lit(MODULUS)))
    return out.withColumn("__h", F.pmod(h * h + 69621 * h + F.col("j") + 7, F.lit(MODULUS)))


def draw(salt: int = 0) -> Column:
    """A number in [0, 1) from ``__h``."""
    h = F.col("__h")
    return F.pmod(F.pmod(h * h + 48271 * h + 11 + salt, F.lit(MODULUS)) * 69621, F.lit(MODULUS)) / F.lit(float(MODULUS))


def sphere_samples(cells: DataFrame, t, side: float, dim: int, sampler: str = "equispaced", seed=0) -> DataFrame:
    """``cells`` once for each sample j with its place q0.. on the cell's circumscribed sphere.

    Their number ``t`` and the seed may be columns, as each epoch has its own.
    """
    radius = side * math.sqrt(dim) / 2
    count = F.lit(2) if dim == 1 else t if isinstance(t, Column) else F.lit(t)
    out = cells.withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), count.cast("long") - 1)))
    if dim > 2 or sampler == "uniform":
        out = with_draws(out, dim, seed)
    if dim == 1:
        ways = [F.when(F.col("j") == 0, -1.0).otherwise(1.0)]
    elif dim == 2:
        turn = F.col("j") / count.cast("double") if sampler == "equispaced" else draw()
        ways = [F.cos(2 * math.pi * turn), F.sin(2 * math.pi * turn)]
    else:
        normal = [F.sqrt(-2 * F.log(draw(2 * i + 1) + 1e-12)) * F.cos(2 * math.pi * draw(2 * i + 2)) for i in range(dim)]
        out = out.withColumns({f"u{i}": v for i, v in enumerate(normal)})
        norm = F.sqrt(sum((F.col(f"u{i}") * F.col(f"u{i}") for i in range(dim)), F.lit(0.0)))
        ways = [F.col(f"u{i}") / norm for i in range(dim)]
    # the row number times zero keeps the optimizer from writing all steps out anew inside a filter on a place
    still = F.monotonically_increasing_id() * F.lit(0.0) if dim > 2 or (dim == 2 and sampler == "uniform") else F.lit(0.0)
    out = out.withColumns({f"q{i}": F.col(f"s{i}") + (F.col(f"k{i}") + 0.5) * side + radius * w + still for i, w in enumerate(ways)})
    return out.drop("__h", *(f"u{i}" for i in range(dim)))


def cap_fraction(eps: float, dim: int) -> float:
    """The share of a cell's sphere (radius eps) that a unit ball over a point eps^2 from the centre covers at least."""
    b = (3 * eps**2 + eps**4) / (2 + 2 * eps**2)
    q = b / eps
    if q >= 1:
        return 0.0
    if dim == 1:
        return 0.5
    if dim == 2:
        return math.acos(q) / math.pi
    steps = 20_000
    area = lambda top: sum((1 - ((i + 0.5) * top / steps) ** 2) ** ((dim - 3) / 2) for i in range(steps)) * top / steps
    return 0.5 - area(q) / (2 * area(1.0))


def grid_eps(factor: float, dim: int) -> float:
    """The largest grid eps whose cap fraction is still ``factor``."""
    low, high = 0.0, 0.9
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if cap_fraction(mid, dim) >= factor else (low, mid)
    return low


def sample_budget(n: int, eps: float, c: float = 1.0, rule: str = "paper", dim: int = 2, failure: float = 0.01, delta: float = 0.05) -> int:
    """Samples for each cell: c eps^-2 ln n, or (``lean``) what one good cell needs to fail with that probability only."""
    if rule == "paper":
        return max(1, math.ceil(c * math.log(max(n, 2)) / eps**2))
    f = cap_fraction(eps, dim)
    return max(1, math.ceil(math.log(1 / failure) * (1 - f + delta) / delta))


def lean_budget(n: Column, eps: float, dim: int, delta: float = 0.05) -> Column:
    """The lean rule of ``sample_budget`` for a failure of one in ``n``, n a column."""
    return F.greatest(F.lit(1), F.ceil(F.log(n.cast("double")) * (1 - cap_fraction(eps, dim) + delta) / delta).cast("int"))


def check_points(points: DataFrame, coords: list[str], weight: str | None = "w") -> None:
    """Raise for NaN coordinates and, where a method needs it, negative weights."""
    bad = F.lit(False)
    for c in coords:
        bad = bad | F.isnan(F.col(c).cast("double"))
    if weight:
        bad = bad | (F.col(weight) < 0)
    if not points.where(bad).isEmpty():
        raise ValueError("NaN coordinates or negative weights; ball methods take neither")


def collapse(points: DataFrame, keys: list[str], weight: str = "w") -> DataFrame:
    """Equal points as one, with the sum of their weights."""
    return points.groupBy(*keys).agg(F.sum(weight).alias(weight))


def within_join(left: DataFrame, right: DataFrame, reach: float, left_xy=("x", "y"), right_xy=("x2", "y2")) -> DataFrame:
    """Pairs of rows at most ``reach`` apart, as an equi-join on cells: the right side goes to 3 x 3 cells."""
    lx, ly = (F.col(c) for c in left_xy)
    rx, ry = (F.col(c) for c in right_xy)
    a = left.withColumn("__cx", F.floor(lx / reach).cast("long")).withColumn("__cy", F.floor(ly / reach).cast("long"))
    b = right.withColumn("__cx", F.explode(F.sequence((F.floor(rx / reach) - 1).cast("long"), (F.floor(rx / reach) + 1).cast("long")))).withColumn("__cy", F.explode(F.sequence((F.floor(ry / reach) - 1).cast("long"), (F.floor(ry / reach) + 1).cast("long"))))
    near = F.pow(lx - rx, F.lit(2.0)) + F.pow(ly - ry, F.lit(2.0)) <= reach * reach * (1 + TOL)
    return a.join(b, ["__cx", "__cy"]).where(near).drop("__cx", "__cy")


def depth_at(places: DataFrame, points: DataFrame, radius: float, kind: str = "weight", color: str = "color") -> DataFrame:
    """``places`` (q_id, x, y) with depth: the weight, count or distinct colours of ``points`` within the radius.

    Equal places are asked once and equal points meet them once.  The points stand in nine cells, which a scan's size does
    not show, so neither side may be broadcast by it.
    """
    once = places.select("x", "y").distinct()
    at = [F.col("x").alias("x2"), F.col("y").alias("y2")]
    if kind == "color":
        near = within_join(once, points.select(*at, F.col(color).alias("hue")).distinct().hint("merge"), radius)
        found = near.select("x", "y", "hue").distinct().groupBy("x", "y").agg(F.count("*").alias("depth"))
    else:
        held = points.groupBy(*at).agg((F.sum("w") if kind == "weight" else F.count("*")).alias("w"))
        found = within_join(once, held.hint("merge"), radius).groupBy("x", "y").agg(F.sum("w").alias("depth"))
    return places.join(found.hint("merge"), ["x", "y"], "left").select(*places.columns, F.coalesce("depth", F.lit(0)).cast("long").alias("depth"))
