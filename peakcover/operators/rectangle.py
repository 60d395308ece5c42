"""Exact rectangles and boxes: weighted, unweighted and coloured, one or many sizes.

The best closed rectangle can be moved until its left and lower edges pass through covered points.  The sweeps send
every point to the few cells in which such a corner can lie and solve each cell in n log n steps; the coloured one
first turns each colour into disjoint ranges.  A cell of more than ``most`` points is split, and what covers a part
of it wholly is added up before the shuffle.  The forms by frames need no kernel: for every left point the points
within reach meet it through an equi-join on cells, so they cost the number of near pairs.  Weights must not be
negative.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import branch, range_kernels

#: Cells are this much smaller than the sides, so that a range always holds an end of its cell.
SHRINK = 1 - 2.0**-20
#: Rows of small cells that are solved at once.
AT_ONCE = 50_000


def _span(c: str, side: float, lo: str, hi: str, by=1) -> dict:
    """The first and last cell (of a ``by``-th of a side) in which an edge can lie that reaches ``c``."""
    step = max(side, 1e-9) * SHRINK
    return {lo: F.floor((F.col(c) - side) * by / step - 2.0**-30).cast("long"), hi: F.floor(F.col(c) * by / step).cast("long")}


def _corners(points: DataFrame, a: float, b: float, most: int, value: str, whole) -> DataFrame:
    """(by, fx, fy, x, y, own_x, own_y, value): the rows of each cell; x and y are null for what covers it wholly."""
    rows = points.withColumns(_span("x", a, "x0", "x1") | _span("y", b, "y0", "y1"))
    rows = rows.withColumn("cx", F.explode(F.sequence("x0", "x1"))).withColumn("cy", F.explode(F.sequence("y0", "y1"))).drop("x0", "x1", "y0", "y1")
    hot = rows.groupBy("cx", "cy").agg(F.count("*").alias("n")).where(F.col("n") > most).select("cx", "cy", F.ceil(F.lit(4) * F.col("n") / most).cast("long").alias("by"))
    rows = rows.join(hot, ["cx", "cy"], "left").withColumn("by", F.coalesce("by", F.lit(1).cast("long")))
    rows = rows.withColumns(_span("x", a, "x0", "x1", F.col("by")) | _span("y", b, "y0", "y1", F.col("by")))
    for c in "xy":  # parts of the cell; a part between the ends of a range is covered wholly
        rows = rows.withColumn(f"f{c}", F.explode(F.expr(f"sequence(least(greatest({c}0, c{c} * by), c{c} * by + by - 1), greatest(least({c}1, c{c} * by + by - 1), c{c} * by))")))
        rows = rows.withColumn(f"own_{c}", F.expr(f"f{c} = greatest(least({c}1, c{c} * by + by - 1), c{c} * by) AND floor({c} / {max(a if c == 'x' else b, 1e-9) * SHRINK!r}D) = c{c}"))
        rows = rows.withColumn(f"in_{c}", F.expr(f"{c}0 < f{c} AND f{c} < {c}1"))
    cell = ["by", "fx", "fy"]
    part = rows.where("NOT (in_x AND in_y)").select(*cell, "x", "y", "own_x", "own_y", value)
    none = F.lit(None).cast("double")
    full = whole(rows.where("in_x AND in_y"), cell).select(*cell, none.alias("x"), none.alias("y"), F.lit(False).alias("own_x"), F.lit(False).alias("own_y"), value)
    return part.unionByName(full)


def _by_cells(batches: Iterator[pd.DataFrame], cell: list[str]) -> Iterator[pd.DataFrame]:
    """Whole cells from sorted batches, many small ones together."""
    held, n, key = [], 0, None
    for pdf in batches:
        if not len(pdf):
            continue
        if n >= AT_ONCE:
            cut = int((pdf[cell] != key).any(axis=1).to_numpy().argmax()) if (pdf[cell].iloc[-1] != key).any() else len(pdf)
            if cut < len(pdf):
                yield pd.concat([*held, pdf.iloc[:cut]])
                held, n, pdf = [], 0, pdf.iloc[cut:]
        held.append(pdf)
        n += len(pdf)
        key = pdf[cell].iloc[-1]
    if held:
        yield pd.concat(held)


def _swept(rows: DataFrame, a: float, b: float, value: str, coloured: bool, kind: str) -> DataFrame:
    """(x0, y0, depth) of the best cell; one row from each partition meets in the last step."""
    cell = ["by", "fx", "fy"]

    def solve(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in _by_cells(batches, cell):
            number = pdf.groupby(cell, sort=False).ngroup().to_numpy()
            held = pd.factorize(pdf[value], use_na_sentinel=False)[0] if coloured else pdf[value].to_numpy()
            best = range_kernels.solve_cells(number, *(pdf[c].to_numpy(np.float64) for c in "xy"), pdf.own_x.to_numpy(bool), pdf.own_y.to_numpy(bool), held, a, b, coloured)
            if best:
                yield pd.DataFrame({"depth": [best[0]], "x": [best[1]], "y": [best[2]]})

    got = rows.repartition(*cell).sortWithinPartitions(*cell).mapInPandas(solve, f"depth {kind}, x double, y double")
    return got.agg(F.max(F.struct("depth", (-F.col("x")).alias("bx"), (-F.col("y")).alias("by"))).alias("m")).where("m IS NOT NULL").select((-F.col("m.bx")).alias("x0"), (-F.col("m.by")).alias("y0"), F.col("m.depth").alias("depth"))


def exact_rectangle(points: DataFrame, a: float, b: float, most: int = 200_000) -> DataFrame:
    """(x0, y0, weight) of the best a x b rectangle, in n log n steps a cell."""
    base = points.groupBy(F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y")).agg(F.sum("w").alias("w"))
    rows = _corners(base, a, b, most, "w", lambda r, cell: r.groupBy(*cell).agg(F.sum("w").alias("w")))
    return _swept(rows, a, b, "w", False, base.schema["w"].dataType.simpleString()).withColumnRenamed("depth", "weight")


def coloured_rectangle(points: DataFrame, a: float, b: float, color: str = "color", most: int = 200_000) -> DataFrame:
    """(x0, y0, colors) of the a x b rectangle with most distinct colours (a null is none), in n log n steps a cell."""
    base = points.select(F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), F.col(color).alias("hue")).where("hue IS NOT NULL").distinct()
    rows = _corners(base, a, b, most, "hue", lambda r, cell: r.select(*cell, "hue").distinct())
    return _swept(rows, a, b, "hue", True, "long").withColumnRenamed("depth", "colors")


def _beside(points: DataFrame, a: float, b: float, keep: list[str]) -> DataFrame:
    """(i, xi, yi, y, keep..): for every point those at most a to its right and b above or below."""
    left = points.select(F.col("id").alias("i"), F.col("x").alias("xi"), F.col("y").alias("yi"), F.floor(F.col("x") / max(a, 1e-9)).cast("long").alias("cx"), F.floor(F.col("y") / max(b, 1e-9)).cast("long").alias("cy"))
    cells = lambda c, side, back: F.explode(F.sequence((F.floor(F.col(c) / max(side, 1e-9)) - 1).cast("long"), (F.floor(F.col(c) / max(side, 1e-9)) + back).cast("long")))
    right = points.select("x", "y", *keep).withColumn("cx", cells("x", a, 0)).withColumn("cy", cells("y", b, 1))
    return left.join(right, ["cx", "cy"]).where((F.col("x") >= F.col("xi")) & (F.col("x") <= F.col("xi") + a) & (F.abs(F.col("y") - F.col("yi")) <= b)).drop("cx", "cy")


def rectangle_by_frames(points: DataFrame, a: float, b: float) -> DataFrame:
    """(x0, y0, weight) of the best a x b rectangle, with a RANGE frame for each left point."""
    base = points.groupBy("x", "y").agg(F.min("id").alias("id"), F.sum("w").alias("w"))
    frame = Window.partitionBy("i").orderBy("y").rangeBetween(0, int(b) if float(b).is_integer() else b)
    swept = _beside(base, a, b, ["w"]).withColumn("s", F.sum("w").over(frame)).where("y <= yi")
    return swept.agg(F.max(F.struct("s", (-F.col("xi")).alias("bx"), (-F.col("y")).alias("by"))).alias("m")).where("m IS NOT NULL").select((-F.col("m.bx")).alias("x0"), (-F.col("m.by")).alias("y0"), F.col("m.s").cast("long").alias("weight"))


def coloured_by_islands(points: DataFrame, a: float, b: float, color: str = "color") -> DataFrame:
    """(x0, y0, colors) of the a x b rectangle with most distinct colours, by frames.

    For a left point, each colour's lower edges that reach one of its points form islands; their starts and ends
    are summed along the axis, so no set of colours is kept.
    """
    base = points.select("x", "y", color).where(F.col(color).isNotNull()).distinct().withColumn("id", F.xxhash64("x", "y"))
    left = base.groupBy("x", "y").agg(F.min("id").alias("id"))
    met = _coloured_beside(left, base, a, b, color)
    # a lower edge y0 reaches the colour's point y for y0 in [y - b, y]
    ordered = Window.partitionBy("i", color).orderBy("lo", "hi").rowsBetween(Window.unboundedPreceding, -1)
    spans = met.select("i", "xi", color, (F.col("y") - b).alias("lo"), F.col("y").alias("hi")).withColumn("reach", F.max("hi").over(ordered))
    spans = spans.withColumn("fresh", F.expr("if(reach IS NULL OR lo > reach, 1, 0)")).withColumn("island", F.sum("fresh").over(Window.partitionBy("i", color).orderBy("lo", "hi").rowsBetween(Window.unboundedPreceding, 0)))
    islands = spans.groupBy("i", "xi", color, "island").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    events = islands.select("i", "xi", F.explode(F.array(F.struct(F.col("lo").alias("at"), F.lit(0).alias("kind"), F.lit(1).alias("d")), F.struct(F.col("hi").alias("at"), F.lit(1).alias("kind"), F.lit(-1).alias("d")))).alias("e")).select("i", "xi", "e.*")
    swept = events.withColumn("n", F.sum("d").over(Window.partitionBy("i").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)))
    return swept.agg(F.max(F.struct("n", (-F.col("xi")).alias("bx"), (-F.col("at")).alias("by"))).alias("m")).where("m IS NOT NULL").select((-F.col("m.bx")).alias("x0"), (-F.col("m.by")).alias("y0"), F.col("m.n").cast("long").alias("colors"))


def _coloured_beside(left: DataFrame, points: DataFrame, a: float, b: float, color: str) -> DataFrame:
    own = left.select(F.col("id").alias("i"), F.col("x").alias("xi"), F.col("y").alias("yi"), F.floor(F.col("x") / max(a, 1e-9)).cast("long").alias("cx"), F.floor(F.col("y") / max(b, 1e-9)).cast("long").alias("cy"))
    cells = lambda c, side, back: F.explode(F.sequence((F.floor(F.col(c) / max(side, 1e-9)) - 1).cast("long"), (F.floor(F.col(c) / max(side, 1e-9)) + back).cast("long")))
    right = points.select("x", "y", color).withColumn("cx", cells("x", a, 0)).withColumn("cy", cells("y", b, 1))
    return own.join(right, ["cx", "cy"]).where((F.col("x") >= F.col("xi")) & (F.col("x") <= F.col("xi") + a) & (F.abs(F.col("y") - F.col("yi")) <= b)).drop("cx", "cy")


def batched_rectangle(points: DataFrame, sizes) -> DataFrame:
    """(q_id, weight): one exact run for each (q_id, a, b)."""
    out = None
    for q, a, b in sizes:
        one = exact_rectangle(points, a, b).select(F.lit(q).alias("q_id"), "weight")
        out = one if out is None else out.union(one)
    return out


def rectangle_by_candidates(points: DataFrame, a: float, b: float) -> DataFrame:
    """The brute-force optimum over all left and lower edges of near pairs of points."""
    base = points.groupBy("x", "y").agg(F.min("id").alias("id"), F.sum("w").alias("w"))
    edges = _beside(base, a, b, []).where("y <= yi").select(F.col("xi").alias("x0"), F.col("y").alias("y0")).distinct()
    e = edges.withColumn("cx", F.floor(F.col("x0") / max(a, 1e-9)).cast("long")).withColumn("cy", F.floor(F.col("y0") / max(b, 1e-9)).cast("long"))
    cells = lambda c, side: F.explode(F.sequence((F.floor(F.col(c) / max(side, 1e-9)) - 1).cast("long"), F.floor(F.col(c) / max(side, 1e-9)).cast("long")))
    p = base.select("x", "y", "w").withColumn("cx", cells("x", a)).withColumn("cy", cells("y", b))
    met = e.join(p, ["cx", "cy"]).where((F.col("x") >= F.col("x0")) & (F.col("x") <= F.col("x0") + a) & (F.col("y") >= F.col("y0")) & (F.col("y") <= F.col("y0") + b))
    return met.groupBy("x0", "y0").agg(F.sum("w").alias("s")).agg(F.coalesce(F.max("s"), F.lit(0)).cast("long").alias("weight"))


def exact_box(points: DataFrame, sides: tuple[float, ...], most: int | None = None) -> DataFrame:
    """(weight,) of the best closed box in any dimension from two, by branch and bound in cells of the box's size.

    A cell of the box's size is covered by one box, so the heaviest gives a depth to beat, and cells that cannot beat it are
    left out before the kernel.  A caller may name the ``most`` points that a cell which could beat it takes.
    """
    axes = range(len(sides))
    keys = [f"k{i}" for i in axes]
    base = points.groupBy(*(F.get("pos", F.lit(i)).cast("double").alias(f"p{i}") for i in axes)).agg(F.sum("w").alias("w")).dropna()
    kind = base.schema["w"].dataType.simpleString()
    reached = base.withColumns({f"k{i}": _span(f"p{i}", side, "lo", "hi")["hi"] for i, side in enumerate(sides)}).groupBy(*keys).agg(F.sum("w").alias("held")).agg(F.max("held")).first()[0] or 0
    rows = base
    for i, side in enumerate(sides):
        rows = rows.withColumns(_span(f"p{i}", side, "lo", "hi")).withColumn(f"k{i}", F.explode(F.sequence("lo", "hi"))).withColumn(f"own{i}", F.col(f"k{i}") == F.col("hi")).drop("lo", "hi")

    def solve(pdf: pd.DataFrame, key, known, share: int | None, nodes: int | None):
        at, own = pdf[[f"p{i}" for i in axes]].to_numpy(np.float64), pdf[[f"own{i}" for i in axes]].to_numpy(bool)
        if share is not None:
            own[:, 0] &= np.isin(at[:, 0], np.array_split(np.unique(at[own[:, 0], 0]), branch.SHARES)[share])
        return branch.best_box(at, own, pdf.w.to_numpy(), sides, known, nodes)

    best = branch.best_of_cells(rows, keys, reached, solve, kind, most)
    return points.sparkSession.range(1).select(F.lit(best).cast(kind).alias("weight"))
