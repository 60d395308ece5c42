"""Deepest-sample placement of a ball: weighted and coloured, static.

Balls of radius 1 stand around the scaled points.  Every cell of every shifted grid that a ball meets has the
same sample points on its sphere, whoever computes them; a sample's depth is the sum over the balls that hold
it.  Nothing but (grid, cell, sample, partial sum) is shuffled.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G


@dataclass(frozen=True)
class BallPlan:
    """The numbers of a run: grids, cell side and samples for each cell."""

    eps: float
    dim: int
    samples: int
    mode: str = "thin"
    sampler: str = "equispaced"
    seed: int = 0

    @property
    def side(self) -> float:
        return 2 * self.eps / math.sqrt(self.dim)

    @property
    def grids(self) -> list:
        return G.shifted_grids(self.side, self.eps**2, self.dim, self.mode)

    @property
    def cell(self) -> list[str]:
        return ["g"] + [f"k{i}" for i in range(self.dim)]

    @property
    def factor(self) -> float:
        """What share of the best weight the deepest sample has: surely for equispaced samples, else on average."""
        f = G.cap_fraction(self.eps, self.dim)
        return math.floor(f * self.samples) / self.samples if self.sampler == "equispaced" and self.dim == 2 else f


def plan(eps: float, dim: int = 2, n: int = 2, samples: int | None = None, rule: str = "lean", c: float = 1.0, mode: str = "thin", sampler: str | None = None, seed: int = 0) -> BallPlan:
    if not 0 < eps < 0.5:
        raise ValueError("eps lies between 0 and 1/2")
    chosen = sampler or {1: "endpoints", 2: "equispaced"}.get(dim, "uniform")
    return BallPlan(eps, dim, samples or G.sample_budget(n, eps, c, rule, dim), mode, chosen, seed)


def gathered(balls: DataFrame, dim: int, side: float = 4.0, shares: int = 16) -> DataFrame:
    """``balls`` with near ones in one task, before each becomes many rows, so that partial sums are worth making.

    It moves a row for each ball, not for each sample; a dense place is dealt out in ``shares``.
    """
    if balls.isStreaming:
        return balls
    n = int(balls.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    at = [F.floor(F.col(f"c{i}") / side) for i in range(min(dim, 2))]
    return balls.repartition(n, *at, F.pmod(F.xxhash64(*(f"c{i}" for i in range(dim))), F.lit(shares)))


def sample_hits(balls: DataFrame, p: BallPlan, keep: list[str], t=None, seed=None) -> DataFrame:
    """(g, k.., j, keep..): a row for each sample inside a ball; number and seed of the samples may be columns."""
    cells = G.ball_cells(gathered(balls, p.dim), p.grids, p.side, p.dim)
    hits = G.sphere_samples(cells, p.samples if t is None else t, p.side, p.dim, p.sampler, p.seed if seed is None else seed)
    away = sum((F.pow(F.col(f"q{i}") - F.col(f"c{i}"), F.lit(2.0)) for i in range(p.dim)), F.lit(0.0))
    return hits.where(away <= 1 + G.TOL).select(*p.cell, "j", *keep)


def sample_depth(balls: DataFrame, p: BallPlan, weight: str = "w") -> DataFrame:
    """The depth of every sample that some ball holds."""
    return sample_hits(balls, p, [weight]).groupBy(*p.cell, "j").agg(F.sum(weight).alias("depth"))


def colour_depth(balls: DataFrame, p: BallPlan, color: str = "color") -> DataFrame:
    """The number of distinct colours over every sample, by two aggregations without a set in memory."""
    once = sample_hits(balls, p, [color]).groupBy(*p.cell, "j", color).agg(F.lit(1).alias("one"))
    return once.groupBy(*p.cell, "j").agg(F.count("*").alias("depth"))


def colour_depth_by_bits(balls: DataFrame, p: BallPlan, color: str = "color") -> DataFrame:
    """The same by one aggregation, for at most 63 colours (checked): a bit for each."""
    known = [r[0] for r in balls.select(color).distinct().sort(color).limit(64).collect()]
    if len(known) > 63:
        raise ValueError("more than 63 colours; use colour_depth")
    bits = F.create_map(*(v for i, c in enumerate(known) for v in (F.lit(c), F.lit(1 << i)))) if known else F.lit(None)
    return sample_hits(balls.withColumn("bit", bits[F.col(color)]), p, ["bit"]).groupBy(*p.cell, "j").agg(F.bit_count(F.bit_or("bit")).cast("long").alias("depth"))


def colour_depth_by_order(balls: DataFrame, p: BallPlan, color: str = "color") -> DataFrame:
    """The same by sorting each sample's balls by colour and counting changes, as a cross-check."""
    from pyspark.sql import Window

    seen = Window.partitionBy(*p.cell, "j").orderBy(color)
    hits = sample_hits(balls, p, [color]).withColumn("before", F.lag(color).over(seen))
    return hits.groupBy(*p.cell, "j").agg(F.sum(F.expr(f"if(before IS NULL OR before <> {color}, 1L, 0L)")).alias("depth"))


def cell_bounds(balls: DataFrame, p: BallPlan, weight: str = "w") -> DataFrame:
    """No sample of a cell is deeper than the weight of the balls that meet it."""
    return G.ball_cells(gathered(balls, p.dim), p.grids, p.side, p.dim).groupBy(*p.cell).agg(F.sum(weight).alias("bound"))


PROBES = 32


def pruned_depth(balls: DataFrame, p: BallPlan, weight: str = "w") -> DataFrame:
    """Sample depths in the cells that can hold the best: bounds first, then samples where the bound reaches a known depth.

    Bounds are sums by cell, so only partial sums are shuffled.  The known depth is the deepest sample of the cells
    with the largest bounds, one number that crosses the driver; then cells are listed again, and only those that
    can still hold the best get samples.
    """
    from ..plans.staging import staged

    bounds = staged(cell_bounds(balls, p, weight), "cell-bounds")
    away = sum((F.pow(F.col(f"q{i}") - F.col(f"c{i}"), F.lit(2.0)) for i in range(p.dim)), F.lit(0.0))

    def deepen(cells):
        rows = G.ball_cells(gathered(balls, p.dim), p.grids, p.side, p.dim).join(cells.select(*p.cell), p.cell, "left_semi")
        return G.sphere_samples(rows, p.samples, p.side, p.dim, p.sampler, p.seed).where(away <= 1 + G.TOL).groupBy(*p.cell, "j").agg(F.sum(weight).alias("depth"))

    known = deepen(F.broadcast(bounds.orderBy(F.desc("bound"), *p.cell).limit(PROBES))).agg(F.max("depth")).first()[0]
    return deepen(bounds if known is None else bounds.where(F.col("bound") >= F.lit(known)))


def deepest(depths: DataFrame, p: BallPlan, k: int = 1) -> DataFrame:
    """The k deepest samples of different cells (depth, then the smaller grid, cell and sample), with their place."""
    own = depths.groupBy(*p.cell).agg(F.max(F.struct("depth", (-F.col("j")).alias("back"))).alias("b")).select(*p.cell, F.col("b.depth").alias("recorded"), (-F.col("b.back")).alias("j"))
    best = own.orderBy(F.desc("recorded"), *p.cell).limit(k)
    shifts = F.array(*(F.array(*(F.lit(float(s)) for s in shift)) for _, shift in p.grids))
    placed = best.withColumns({f"s{i}": F.get(F.get(shifts, F.col("g")), F.lit(i)) for i in range(p.dim)}).withColumn("only", F.col("j"))
    return G.sphere_samples(placed, p.samples, p.side, p.dim, p.sampler, p.seed).where("j = only").drop("only", *(f"s{i}" for i in range(p.dim)))


def true_depth(best: DataFrame, balls: DataFrame, p: BallPlan, weight: str | None = "w", color: str | None = None) -> DataFrame:
    """``best`` (k rows at most) with the depth over all balls, which is never below the recorded one."""
    b = best.select(*p.cell, "j", "recorded", *(f"q{i}" for i in range(p.dim)))
    near = sum((F.pow(F.col(f"q{i}") - F.col(f"c{i}"), F.lit(2.0)) for i in range(p.dim)), F.lit(0.0)) <= 1 + G.TOL
    met = balls.crossJoin(F.broadcast(b)).where(near)  # k rows are broadcast
    keys = [*p.cell, "j", "recorded", *(f"q{i}" for i in range(p.dim))]
    if color:
        return met.select(*keys, color).distinct().groupBy(*keys).agg(F.count("*").alias("depth"))
    return met.groupBy(*keys).agg(F.sum(weight).alias("depth"))


def few_colours(balls: DataFrame, color: str, most: int = 63) -> bool:
    return balls.select(color).distinct().limit(most + 1).count() <= most


def static_ball(points: DataFrame, radius: float, eps: float = 0.4, dim: int = 2, coords=("x", "y"), pos: str | None = None, color: str | None = None, samples: int | None = 16, prune: bool = False, k: int = 1, collapse: bool = True, **options) -> DataFrame:
    """The deepest-sample placement: place (q0.. scaled back), recorded and true depth, grid, cell and sample.

    Balls of equal place (and colour) are one, which loses nothing; with at most 63 colours each is a bit.
    """
    names = None if pos else list(coords)[:dim]
    at = [f"c{i}" for i in range(dim)]
    balls = G.to_dual(points, radius, names, pos, dim)
    if collapse:
        balls = balls.select(*at, color).distinct() if color else G.collapse(balls, at)
    p = plan(eps, dim, samples=samples, **options)
    if color:
        depths = colour_depth_by_bits(balls, p, color) if few_colours(balls, color) else colour_depth(balls, p, color)
    else:
        depths = pruned_depth(balls, p) if prune else sample_depth(balls, p)
    best = true_depth(deepest(depths, p, k), balls, p, color=color)
    return best.withColumns({f"q{i}": F.col(f"q{i}") * radius for i in range(p.dim)})


def own_cell_depth(balls: DataFrame, p: BallPlan, weight: str = "w", color: str | None = None) -> DataFrame:
    """Sample depths in the cells that hold a point, for dimensions where a ball meets too many cells to list.

    Samples and balls meet by the unit cells of their first two coordinates.
    """
    at, what = [f"c{i}" for i in range(p.dim)], color or weight
    grids = G.with_grids(gathered(balls.select(*at).distinct(), p.dim), p.grids)
    cells = grids.withColumns({f"k{i}": F.floor((F.col(f"c{i}") - F.col(f"s{i}")) / p.side).cast("long") for i in range(p.dim)}).select(*p.cell, *(f"s{i}" for i in range(p.dim))).distinct()
    samples = G.sphere_samples(cells, p.samples, p.side, p.dim, p.sampler, p.seed).select(*p.cell, "j", *(f"q{i}" for i in range(p.dim)))
    met = G.within_join(samples, balls.select(*at, what), 1.0, ("q0", "q1"), ("c0", "c1"))
    away = sum((F.pow(F.col(f"q{i}") - F.col(f"c{i}"), F.lit(2.0)) for i in range(p.dim)), F.lit(0.0))
    hits = met.where(away <= 1 + G.TOL)
    if color:
        return hits.select(*p.cell, "j", color).distinct().groupBy(*p.cell, "j").agg(F.count("*").alias("depth"))
    return hits.groupBy(*p.cell, "j").agg(F.sum(weight).alias("depth"))


def around_points(balls: DataFrame, dim: int, reach: float, color: str | None = None, weight: str = "w") -> DataFrame:
    """(top): the most within ``reach`` of a ball's centre.  With 1 a real depth, with 2 a bound that no place passes."""
    if dim == 1:  # a line in the plane
        balls, dim = balls.withColumn("c1", F.lit(0.0)), 2
    own = balls.select(*(F.col(f"c{i}").alias(f"a{i}") for i in range(dim))).distinct().withColumn("__q", F.monotonically_increasing_id())
    near = sum((F.pow(F.col(f"a{i}") - F.col(f"c{i}"), F.lit(2.0)) for i in range(dim)), F.lit(0.0)) <= reach * reach * (1 + G.TOL)
    met = G.within_join(own, balls.select(*(f"c{i}" for i in range(dim)), color or weight), reach, ("a0", "a1"), ("c0", "c1")).where(near)
    per = met.select("__q", color).distinct().groupBy("__q").agg(F.count("*").alias("n")) if color else met.groupBy("__q").agg(F.sum(weight).alias("n"))
    return per.agg(F.max("n").alias("top"))
