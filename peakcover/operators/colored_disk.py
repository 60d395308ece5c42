"""Coloured disks in the plane over shifted unit grids: output-sensitive exact, and (1 - eps) by sampling colours.

Every disk goes to the cells it meets; in a cell only disks that hold one of its four corners matter for the
near optimum, so a cell's distinct colours are at most four times the optimum.  In some grid an optimal place on
a circle is near its cell's centre: disks that come nowhere near, circles that do not pass there, and cells whose
colours do not pass a known depth are skipped.  What remains of a cell is solved exactly by a kernel.

``strips_exact`` has neither grid nor corner filter: vertical strips part the plane, and each holds the piece of
the trapezoidal map between its walls.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G
from . import branch
from .cell_kernels import KERNELS

SIDE, DELTA = 1.0, 0.25
NEAR = DELTA + 1e-6
PROBES = 12
CELL = ["g", "k0", "k1"]


def corner_disks(points: DataFrame, radius: float, color: str = "color", mode: str = "thin", near_only: bool = False) -> DataFrame:
    """(g, k0, k1, c0, c1, hue): unit disks of every cell that hold a corner of it, or of those the ones that come near its centre."""
    disks = points.select((F.col("x").cast("double") / radius).alias("c0"), (F.col("y").cast("double") / radius).alias("c1"), F.col(color).alias("hue")).distinct()
    cells = G.ball_cells(disks, G.shifted_grids(SIDE, DELTA, 2, mode), SIDE, 2)
    if near_only:
        off = [F.col(f"s{i}") + (F.col(f"k{i}") + 0.5) * SIDE - F.col(f"c{i}") for i in range(2)]
        cells = cells.where(off[0] * off[0] + off[1] * off[1] <= (1 + NEAR) ** 2)
    holds = lambda u, v: F.pow(F.col("s0") + (F.col("k0") + u) * SIDE - F.col("c0"), F.lit(2.0)) + F.pow(F.col("s1") + (F.col("k1") + v) * SIDE - F.col("c1"), F.lit(2.0)) <= 1 + G.TOL
    return cells.where(holds(0, 0) | holds(0, 1) | holds(1, 0) | holds(1, 1)).select(*CELL, "c0", "c1", "hue")


def corner_depth(points: DataFrame, radius: float, color: str = "color", mode: str = "thin") -> DataFrame:
    """(g, k0, k1, depth): distinct colours over each grid corner that some disk holds."""
    disks = points.select((F.col("x").cast("double") / radius).alias("c0"), (F.col("y").cast("double") / radius).alias("c1"), F.col(color).alias("hue")).distinct()
    out = G.with_grids(disks, G.shifted_grids(SIDE, DELTA, 2, mode))
    for i in range(2):
        out = out.withColumn(f"k{i}", F.explode(F.sequence(F.ceil((F.col(f"c{i}") - F.col(f"s{i}") - 1) / SIDE).cast("long"), F.floor((F.col(f"c{i}") - F.col(f"s{i}") + 1) / SIDE).cast("long"))))
    near = sum((F.pow(F.col(f"s{i}") + F.col(f"k{i}") * SIDE - F.col(f"c{i}"), F.lit(2.0)) for i in range(2)), F.lit(0.0)) <= 1 + G.TOL
    return out.where(near).select(*CELL, "hue").distinct().groupBy(*CELL).agg(F.count("*").alias("depth"))


def best_corner(points: DataFrame, radius: float, color: str = "color") -> int:
    """A real depth that is at least a quarter of the optimum: the estimate, and the first bound for skipping cells."""
    return corner_depth(points, radius, color).agg(F.max("depth")).first()[0] or 0


def cell_colours(disks: DataFrame) -> DataFrame:
    return disks.select(*CELL, "hue").distinct().groupBy(*CELL).agg(F.count("*").alias("colors"))


def output_sensitive(points: DataFrame, radius: float, color: str = "color", engine: str = "sweep", mode: str = "thin", known: int | None = None, prune: bool = True) -> DataFrame:
    """The exact optimum: x, y, depth."""
    from ..plans.staging import staged

    if engine == "branch":
        return by_branches(points, radius, color)
    kernel, shifts = KERNELS[engine], dict(G.shifted_grids(SIDE, DELTA, 2, mode))
    if known is None:
        known = best_corner(points, radius, color)
    disks = staged(corner_disks(points, radius, color, mode, near_only=prune), "corner-disks")

    def solved(rows, floor: int):
        def solve(key, frame):
            import pandas as pd

            centre = tuple(shifts[int(key[0])][i] + (int(key[1 + i]) + 0.5) * SIDE for i in range(2))
            depth, x, y = kernel(frame["c0"].to_numpy(), frame["c1"].to_numpy(), pd.factorize(frame["hue"])[0], floor, centre if prune else None, NEAR)
            return pd.DataFrame({"depth": [depth], "x": [x * radius], "y": [y * radius]})

        return rows.groupBy(*CELL).applyInPandas(solve, "depth long, x double, y double").orderBy(F.desc("depth"), "x", "y").limit(1).select("x", "y", "depth")

    if not prune:
        return solved(disks, 0)
    # the most coloured cells first: what they reach rules out every cell that has no more colours
    colours = staged(cell_colours(disks), "cell-colours")
    top = colours.where(F.col("colors") >= max(1, known)).orderBy(F.desc("colors"), *CELL).limit(PROBES)
    first = staged(solved(disks.join(F.broadcast(top.select(*CELL)), CELL, "left_semi"), known - 1), "first-cells")
    reached = max((first.agg(F.max("depth")).first()[0]) or 0, known - 1)
    rest = colours.where(F.col("colors") > reached).join(F.broadcast(top.select(*CELL)), CELL, "left_anti").select(*CELL)
    return first.union(solved(disks.join(rest, CELL, "left_semi"), reached)).orderBy(F.desc("depth"), "x", "y").limit(1)


def by_branches(points: DataFrame, radius: float, color: str = "color", leaf=None) -> DataFrame:
    """The exact optimum by branch and bound over the place, in cells of the radius: x, y, depth.

    A disk covers any square of side sqrt(2) radii, so the most colourful gives a depth to beat.  Every cell opens some nodes,
    and cells that may still pass the best are settled in shares.  ``leaf`` searches small nodes (``branch.most_colours``).
    """
    from ..plans.staging import staged

    spark = points.sparkSession
    disks = points.where(F.col(color).isNotNull()).select((F.col("x").cast("double") / radius).alias("c0"), (F.col("y").cast("double") / radius).alias("c1"), F.col(color).alias("hue")).dropna().distinct()
    far = F.lit(0.0)
    rows = disks
    for i in range(2):
        rows = rows.withColumn(f"k{i}", F.explode(F.sequence(*(F.floor(F.col(f"c{i}") + s * (1 + 1e-8)).cast("long") for s in (-1, 1)))))
        far = far + F.pow(F.greatest(F.abs(F.col(f"c{i}") - F.col(f"k{i}") - 0.5) - 0.5, F.lit(0.0)), F.lit(2.0))
    rows = staged(rows.where(far <= 1 + 1e-8), "branch-disks")
    held = staged(rows.select("k0", "k1", "hue").distinct().groupBy("k0", "k1").agg(F.count("*").alias("held")), "branch-cells")
    inner = 2**0.5 * (1 - 1e-9)
    known = (disks.select(*(F.floor(F.col(f"c{i}") / inner).alias(f"s{i}") for i in range(2)), "hue").distinct().groupBy("s0", "s1").count().agg(F.max("count")).first()[0] or 0) - 1
    parts = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))  # few bytes, much work: not to be coalesced

    def settle(share: bool, known: int):
        def work(key, frame):
            import numpy as np
            import pandas as pd

            x, y, hue = frame["c0"].to_numpy(), frame["c1"].to_numpy(), pd.factorize(frame["hue"])[0]
            centre = np.array([key[0], key[1]], np.float64) + 0.5
            if not share:
                found = branch.most_colours(x, y, hue, centre, 0.5, known, branch.DIVE, leaf)
            else:
                found = (known, float("nan"), float("nan"))
                for part in range(int(key[2]), 16, branch.SHARES):
                    got = branch.most_colours(x, y, hue, centre + (np.array([part >> 2, part & 3]) - 1.5) / 4, 0.125, found[0], leaf=leaf)
                    found = got if got[0] > found[0] else found
            return pd.DataFrame([found] if found[0] > known else [], columns=["depth", "x", "y"])

        by = ["k0", "k1"]
        met = rows.join(held.where(F.col("held") > F.lit(known)).select(*by), by, "left_semi")
        if share:
            met, by = met.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(branch.SHARES - 1)))), [*by, "share"]
        return met.repartition(parts, *by).groupBy(*by).applyInPandas(work, "depth long, x double, y double").orderBy(F.desc("depth"), "x", "y").first()

    first = settle(False, known)
    last = settle(True, first["depth"] if first else known) or first
    return spark.createDataFrame([(last["x"] * radius, last["y"] * radius, last["depth"])] if last else [], "x double, y double, depth long")


def strips_exact(points: DataFrame, radius: float, color: str = "color", engine: str = "trapezoid", width: float = 0.5) -> DataFrame:
    """The first exact method, without grids or corners: (x, y, depth) from the map of all boundaries, strip by strip.

    A disk goes to the strips of ``width`` radii that it meets, so a task holds the disks near one vertical line.
    """
    kernel = KERNELS[engine]
    disks = points.select((F.col("x").cast("double") / radius).alias("c0"), (F.col("y").cast("double") / radius).alias("c1"), F.col(color).alias("hue")).distinct()
    dealt = disks.withColumn("k0", F.explode(F.sequence(F.floor((F.col("c0") - 1) / width).cast("long"), F.floor((F.col("c0") + 1) / width).cast("long"))))

    def solve(key, frame):
        import pandas as pd

        # a little beyond the walls, so that a place on one is seen from a face
        centre, near = ((int(key[0]) + 0.5) * width, 0.0), width / 2 + 1e-6
        depth, x, y = kernel(frame["c0"].to_numpy(), frame["c1"].to_numpy(), pd.factorize(frame["hue"])[0], 0, centre, near)
        return pd.DataFrame({"depth": [depth], "x": [x * radius], "y": [y * radius]})

    return dealt.groupBy("k0").applyInPandas(solve, "depth long, x double, y double").orderBy(F.desc("depth"), "x", "y").limit(1).select("x", "y", "depth")


def keep_colours(points: DataFrame, rate: float, color: str = "color", seed: int = 0) -> DataFrame:
    """Every colour with all its points, or none, by a hash that any engine has: a filter next to the scan."""
    draw = F.conv(F.substring(F.md5(F.concat_ws("|", F.col(color).cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("long")
    return points.where(draw < F.lit(int(min(1.0, rate) * (1 << 32))))


def sampled(points: DataFrame, radius: float, eps: float, c1: float = 1.0, color: str = "color", seed: int = 0, branch: str = "auto", engine: str = "sweep", estimate: str = "corner") -> DataFrame:
    """(x, y, depth_kept, depth, branch, opt_est, lam, kept_disks): exact where the optimum is small, else on sampled colours.

    The estimate is between a quarter of the optimum and the optimum.  Beyond c1 ln n / eps^2, each colour is
    kept at rate lam = c1 ln n / (eps^2 estimate), the kept disks are solved, and the place is scored over all.
    """
    if not 0 < eps < 1 or c1 <= 0:
        raise ValueError("0 < eps < 1 and c1 > 0")
    from .ball import plan, static_ball

    n = max(2, points.count())
    if estimate == "corner":
        guess = best_corner(points, radius, color)
    else:
        guess = (static_ball(points, radius, 0.4, color=color, samples=plan(0.4, samples=20).samples).first() or {"depth": 0})["depth"]
    level = c1 * math.log(n) / eps**2
    lam = min(1.0, level / max(1, guess))
    way = branch if branch != "auto" else ("exact" if guess <= level else "sample")
    kept = points if way == "exact" else keep_colours(points, lam, color, seed)
    best = output_sensitive(kept, radius, color, engine, known=guess if way == "exact" else None)
    place = best.select("x", "y", F.col("depth").alias("depth_kept")).withColumn("q_id", F.lit(0).cast("long"))
    if place.isEmpty():  # no colour was drawn: the place of the estimate stands
        place = points.select(F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), F.lit(0).cast("long").alias("depth_kept"), F.lit(0).cast("long").alias("q_id")).orderBy("x", "y").limit(1)
    scored = G.depth_at(place, points, radius * (1 + 4e-7), "color", color)
    return scored.select("x", "y", "depth_kept", "depth", F.lit(way).alias("branch"), F.lit(int(guess)).cast("long").alias("opt_est"), F.lit(float(1.0 if way == "exact" else lam)).alias("lam"), F.lit(kept.count()).cast("long").alias("kept_disks"))
