"""Exact disks in the plane (weighted, unweighted, coloured), and exact balls in space: the baselines.

The best closed disk's centre can be moved to the boundary of some point's disk (or to a point), so a sweep
around every boundary sees it.  Neighbours meet through an equi-join on cells; the sweep is a window for each
disk.  Work grows with the pairs of near points: these are the ground truth, not the path for large inputs.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from . import branch

WIDEN = 1e-7
TURN = 2 * math.pi


def neighbours(points: DataFrame, radius: float, keep: list[str], keys: list[str] | None = None) -> DataFrame:
    """(i, x, y, o.., D): for every point the other points within twice the radius, with what is kept of them."""
    left = points.select(*(keys or []), F.col("id").alias("i"), "x", "y", *(F.col(c).alias(f"own_{c}") for c in keep))
    right = points.select(*(keys or []), F.col("id").alias("o"), F.col("x").alias("x2"), F.col("y").alias("y2"), *keep)
    if keys:
        a = left.withColumn("__c", F.explode(F.array(F.lit(0))))
        met = a.drop("__c").join(right, keys).where(F.pow(F.col("x") - F.col("x2"), F.lit(2.0)) + F.pow(F.col("y") - F.col("y2"), F.lit(2.0)) <= 4 * radius * radius * (1 + G.TOL))
    else:
        met = G.within_join(left, right, 2 * radius)
    return met.where("i <> o").withColumn("D", F.sqrt(F.pow(F.col("x2") - F.col("x"), F.lit(2.0)) + F.pow(F.col("y2") - F.col("y"), F.lit(2.0))))


def arcs(near: DataFrame, radius: float) -> DataFrame:
    """(.., lo, hi): the angles on disk i that the other disk covers, lo in [0, 2 pi); hi may pass it."""
    half = F.acos(F.least(F.lit(1.0), F.col("D") / (2 * radius))) + WIDEN
    middle = F.atan2(F.col("y2") - F.col("y"), F.col("x2") - F.col("x"))
    lo = F.pmod(middle - half, F.lit(TURN))
    return near.where("D > 0").withColumn("lo", lo).withColumn("hi", F.col("lo") + 2 * half)


def exact_disk(points: DataFrame, radius: float, weight: str = "w", per_point: bool = False) -> DataFrame:
    """The best disk: x, y (a centre), depth.  ``per_point`` gives the best on every point's boundary instead."""
    base = points.groupBy("x", "y").agg(F.min("id").alias("id"), F.sum(weight).alias("w"))
    near = arcs(neighbours(base, radius, ["w"]), radius)
    ends = near.select("i", "x", "y", F.explode(F.array(F.struct(F.col("lo").alias("at"), F.lit(0).alias("kind"), F.col("w").alias("dw")), F.struct(F.pmod("hi", F.lit(TURN)).alias("at"), F.lit(1).alias("kind"), (-F.col("w")).alias("dw")))).alias("e")).select("i", "x", "y", "e.*")
    wraps = near.where(F.col("hi") >= TURN).select("i", "x", "y", F.lit(-1.0).alias("at"), F.lit(0).alias("kind"), F.col("w").alias("dw"))
    own = base.select(F.col("id").alias("i"), "x", "y", F.lit(-2.0).alias("at"), F.lit(0).alias("kind"), F.col("w").alias("dw"))
    run = Window.partitionBy("i").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    swept = own.union(wraps).union(ends).withColumn("depth", F.sum("dw").over(run))
    place = F.struct("depth", F.when(F.col("at") < 0, 0.0).otherwise(F.col("at")).alias("turn"), "x", "y")
    best = swept.groupBy("i").agg(F.max(place).alias("b")).select("i", (F.col("b.x") + radius * F.cos("b.turn")).alias("x"), (F.col("b.y") + radius * F.sin("b.turn")).alias("y"), F.col("b.depth").alias("depth"))
    return best if per_point else best.orderBy(F.desc("depth"), "x", "y").limit(1).select("x", "y", F.col("depth").cast("long").alias("depth"))


def candidates(points: DataFrame, radius: float) -> DataFrame:
    """(q_id, x, y): the points, and both crossings of every two boundaries."""
    base = points.groupBy("x", "y").agg(F.min("id").alias("id"))
    near = neighbours(base, radius, []).where("i < o AND D > 0")
    h = F.sqrt(F.greatest(F.lit(0.0), F.lit(float(radius * radius)) - F.col("D") * F.col("D") / 4)) / F.col("D")
    mid = [(F.col("x") + F.col("x2")) / 2, (F.col("y") + F.col("y2")) / 2]
    crossing = near.withColumn("side", F.explode(F.array(F.lit(-1.0), F.lit(1.0)))).select((mid[0] - F.col("side") * h * (F.col("y2") - F.col("y"))).alias("x"), (mid[1] + F.col("side") * h * (F.col("x2") - F.col("x"))).alias("y"))
    both = crossing.union(base.select(F.col("x").cast("double"), F.col("y").cast("double")))
    return both.withColumn("q_id", F.monotonically_increasing_id())


def disk_by_candidates(points: DataFrame, radius: float, kind: str = "weight", color: str = "color") -> DataFrame:
    """The brute-force optimum: every candidate's depth, counted by tiles, so that neither candidates nor pairs are rows."""
    from . import tiled

    coloured = kind == "color"
    weight = {"color": F.col(color), "weight": F.col("w"), "count": F.lit(1)}[kind]
    rows = points.select(*((F.col(c).cast("double") / radius).alias(n) for c, n in (("x", "c0"), ("y", "c1"))), weight.alias("value"))
    rows = rows.where("value IS NOT NULL").distinct() if coloured else rows.groupBy("c0", "c1").agg(F.sum("value").alias("value"))

    def solve(x, y, mine, frame):
        import numpy as np
        import pandas as pd

        value = pd.factorize(frame["value"])[0] if coloured else frame["value"].to_numpy()
        place = np.append(True, (np.diff(x) != 0) | (np.diff(y) != 0))  # of colours at one place, one is followed
        own = np.flatnonzero(mine & place)
        best, n = tiled.deepest(x[own], y[own], x, y, value, coloured), len(own)
        for i, j in tiled.near(x, y, own):
            keep = place[j] & (i < j)
            px, py = tiled.crossing_places(x, y, i[keep], j[keep])
            best, n = max(best, tiled.deepest(px, py, x, y, value, coloured), key=lambda b: b[0]), n + len(px)
        return best[0], n

    found = tiled.around(rows, solve, "depth long, candidates long", ["value"])
    return found.agg(F.coalesce(F.max("depth"), F.lit(0)).alias("depth"), F.coalesce(F.sum("candidates"), F.lit(0)).alias("candidates"))


def batched_disk(points: DataFrame, radii: dict[int, float]) -> DataFrame:
    """One exact run for each radius."""
    out = None
    for q, r in sorted(radii.items()):
        one = exact_disk(points, r).select(F.lit(q).alias("q_id"), "depth")
        out = one if out is None else out.union(one)
    return out


def exact_ball3(points: DataFrame, radius: float, most: int | None = None) -> DataFrame:
    """The best closed ball in space, by branch and bound over its centre in cells of the radius; a caller may name the ``most`` points it takes.

    A ball covers any cube of side 2 r / sqrt(3), so the fullest gives a depth to beat.
    """
    if most is not None and points.count() > most:
        raise ValueError(f"more than {most} points")
    base = points.groupBy(*(F.get("pos", F.lit(i)).alias(c) for i, c in enumerate("xyz"))).agg(F.count("*").alias("w")).dropna()
    inner = 2 * radius / 3**0.5 * (1 - 1e-9)
    known = base.groupBy(*(F.floor(F.col(c) / inner) for c in "xyz")).agg(F.sum("w").alias("held")).agg(F.max("held")).first()[0] or 0
    rows, far = base, F.lit(0.0)
    for c in "xyz":
        rows = rows.withColumn(f"k{c}", F.explode(F.sequence(*((F.floor(F.col(c) / radius + s * (1 + 1e-9)).cast("long")) for s in (-1, 1)))))
        far = far + F.pow(F.greatest(F.abs(F.col(c) - (F.col(f"k{c}") + 0.5) * radius) - radius / 2, F.lit(0.0)), F.lit(2.0))
    rows = rows.where(far <= radius * radius * (1 + 1e-8))

    def solve(frame, key, known, share: int | None, nodes: int | None):
        import numpy as np

        p, w, centre = frame[list("xyz")].to_numpy(np.float64), frame["w"].to_numpy(), (np.array(key, np.float64) + 0.5) * radius
        if share is None:
            return branch.best_ball(p, w, radius, centre, radius / 2, known, nodes)
        for part in range(share, 64, branch.SHARES):  # a share has every so manieth of the cell's 64 parts
            at = centre + (np.array([part >> 4, part >> 2 & 3, part & 3]) - 1.5) * radius / 4
            known = branch.best_ball(p, w, radius, at, radius / 8, known)
        return known

    best = branch.best_of_cells(rows, ["kx", "ky", "kz"], known, solve, "long")
    return points.sparkSession.range(1).select(F.lit(best).cast("long").alias("depth"))
