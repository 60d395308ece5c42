"""Deepest samples under inserts and deletes: epochs, replay of a whole log, and recomputation to compare with.

An update adds (or takes off) its weight at every sample inside its ball.  Tiles of the plane follow their own updates in
order and tell between which rounds their deepest sample stays; a round takes the best of the tiles.  What is
shuffled is an update for each tile that it reaches, and a piece for each change of a tile's best.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..plans.staging import staged
from .ball import BallPlan, sample_depth, sample_hits
from .ordering import prefix_sums
from .tile_depths import overlaid, pieces, standing


def live_sizes(log: DataFrame) -> DataFrame:
    """(round, live): how many balls stand after each round."""
    return prefix_sums(log.select("round", "sign"), ["round"], {"live": "sign"}).select("round", "live")


SCAN_ROUNDS = 1 << 16


def assign_epochs(log: DataFrame, rounds: int = SCAN_ROUNDS) -> DataFrame:
    """(epoch, start, base): an epoch ends when the size leaves [base/2, 2 base]; its successor's base is the size then.

    The sizes are cut into blocks of ``rounds`` rounds.  The driver knows each block's least and greatest size, and
    reads a block (that many numbers at most) only if the running epoch ends in it, however many end there.
    """
    spark = log.sparkSession
    sizes = staged(live_sizes(log), "live-sizes")
    ranges = sizes.groupBy(F.expr(f"round div {rounds}").alias("b")).agg(F.min("live").alias("low"), F.max("live").alias("high")).orderBy("b").collect()  # one row a block
    found, base = [], None
    for r in ranges:
        if base is not None and r["low"] * 2 >= base and r["high"] <= 2 * base:
            continue
        block = sizes.where(F.col("round").between(r["b"] * rounds, (r["b"] + 1) * rounds - 1)).orderBy("round").collect()
        for x in block:
            if base is None or x["live"] * 2 < base or x["live"] > 2 * base:
                base = max(1, x["live"])
                found.append((len(found), x["round"], base))
    return spark.createDataFrame(found, "epoch int, start long, base long")


def epoch_ends(epochs: DataFrame) -> DataFrame:
    """Epochs with ``until``, the round the next one starts at (null for the last)."""
    after = epochs.select((F.col("epoch") - 1).alias("epoch"), F.col("start").alias("until"))
    return epochs.join(after, "epoch", "left")


def lifetimes(log: DataFrame) -> DataFrame:
    """(id, x, y, w, born, died): rounds of insert and delete; died is null while it stands."""
    return log.groupBy("id").agg(F.first("x").alias("x"), F.first("y").alias("y"), F.first("w").alias("w"), F.min(F.expr("if(op = 'insert', round, NULL)")).alias("born"), F.max(F.expr("if(op = 'delete', round, NULL)")).alias("died"))


def with_epochs(log: DataFrame, epochs: DataFrame, width: int = 1024) -> DataFrame:
    """The log's rows with their epoch and its base, and at each epoch's start the standing balls once more as inserts.

    Rounds meet epochs in buckets of ``width`` rounds, an equi-join whatever their number; lifetimes meet starts by the
    numbers of the epochs, so that only rows of the result are made.
    """
    top = log.agg(F.max("round")).first()[0] or 0
    ends = epoch_ends(epochs)
    bucket = lambda c: F.expr(f"{c} div {width}")
    spans = ends.withColumn("b", F.explode(F.sequence(bucket("start"), F.expr(f"(coalesce(until - 1, {top}L)) div {width}"))))
    own = log.withColumn("b", bucket("round")).join(F.broadcast(spans), "b").where("round >= start AND (until IS NULL OR round < until)")
    # a ball stands at the starts of the epochs after that of its insert, up to that of its delete
    lives = own.groupBy("id").agg(F.first("x").alias("x"), F.first("y").alias("y"), F.first("w").alias("w"), F.min(F.expr("if(op = 'insert', epoch, NULL)")).alias("came"), F.max(F.expr("if(op = 'delete', epoch, NULL)")).alias("went"))
    last = epochs.agg(F.max("epoch").alias("newest"))
    lives = lives.crossJoin(F.broadcast(last)).withColumn("went", F.coalesce("went", "newest")).where("came < went").withColumn("epoch", F.explode(F.expr("sequence(came + 1, went)")))
    lives = lives.join(F.broadcast(epochs), "epoch").select("epoch", "base", F.col("start").alias("round"), "x", "y", "w", F.lit(1).alias("sign"))
    return own.select("epoch", "base", "round", "x", "y", "w", "sign").union(lives)


def epoch_samples(eps: float, c: float = 1.0) -> F.Column:
    """The samples of a cell in an epoch: c ln(base) / eps^2, one at least."""
    return F.greatest(F.lit(1), F.ceil(F.lit(c / eps**2) * F.log(F.greatest(F.col("base"), F.lit(2)).cast("double")))).cast("int")


def sample_changes(log: DataFrame, radius: float, p: BallPlan, keys: list[str] | None = None, t=None, seed=None) -> DataFrame:
    """(keys.., g, k.., j, round, dw): what each round changes at each sample."""
    keys = keys or []
    extra = [] if t is None else ["base"]
    balls = G.to_dual(log.select(*keys, *extra, "round", "x", "y", (F.col("w") * F.col("sign")).alias("dw")), radius, ["x", "y"])
    return sample_hits(balls, p, [*keys, "round", "dw"], t, seed).groupBy(*keys, *p.cell, "j", "round").agg(F.sum("dw").alias("dw"))


def dyadic(ranges: DataFrame, levels: int) -> DataFrame:
    """Rows with [a, b) once for each dyadic block (level, block) of the range's cover."""
    cut = ranges.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(levels)))).withColumn("size", F.expr("shiftleft(1L, level)"))
    cut = cut.withColumn("lo", F.expr("(a + size - 1) div size")).withColumn("hi", F.expr("b div size"))
    both = F.expr("filter(array(if(lo % 2 = 1, lo, NULL), if(hi % 2 = 1, hi - 1, NULL)), v -> v IS NOT NULL)")
    return cut.where("lo < hi").withColumn("block", F.explode(both)).drop("size", "lo", "hi")


def changes_of(rows: DataFrame, *keys) -> DataFrame:
    return rows.select(*keys, F.col("round").cast("long").alias("round"), "x", "y", (F.col("w") * F.col("sign")).cast("long").alias("dw"))


def round_best(log: DataFrame, radius: float, p: BallPlan) -> DataFrame:
    """(round, live, depth): the deepest sample after every round (0 where nothing stands)."""
    total = log.agg(F.max("round")).first()[0] or 0
    spans = pieces(changes_of(log), radius, p, []).withColumn("b", F.coalesce("b", F.lit(total + 1)))
    return live_sizes(log).join(overlaid(spans, []), "round", "left").select("round", "live", F.coalesce("depth", F.lit(0)).cast("long").alias("depth"))


def replay(log: DataFrame, radius: float, p: BallPlan, budget: float | None = None) -> DataFrame:
    """(epoch, round, depth): the same with epochs, each starting from the standing balls on samples of its own.

    With a budget c every epoch draws new samples, seeded by its number, c ln(base) / eps^2 for a cell; without one
    the plan's samples serve all epochs.
    """
    rows = staged(with_epochs(log, assign_epochs(log)), "epoch-rows")
    fresh = {} if budget is None else {"t": epoch_samples(p.eps, budget), "seed": F.col("epoch")}
    last = rows.groupBy("epoch").agg((F.max("round") + 1).alias("stop"))
    keys = ["epoch"] if budget is None else ["epoch", "base"]
    spans = pieces(changes_of(rows, *keys), radius, p, keys, **fresh).join(F.broadcast(last), "epoch").withColumn("b", F.coalesce("b", "stop"))
    asked = rows.select("epoch", F.col("round").cast("long").alias("round")).distinct()
    return asked.join(overlaid(spans.drop("base", "stop"), ["epoch"]), ["epoch", "round"], "left").select("epoch", "round", F.coalesce("depth", F.lit(0)).cast("long").alias("depth"))


def recompute(log: DataFrame, rounds: list[int], radius: float, p: BallPlan) -> DataFrame:
    """(round, depth) from scratch at the given rounds: the standing balls of each, all over again; equal balls as one."""
    asked = log.sparkSession.createDataFrame([(int(r),) for r in rounds], "asked long")
    depths = standing(lifetimes(log), rounds, radius, p).groupBy("asked").agg(F.max("depth").alias("depth"))
    return asked.join(depths, "asked", "left").select(F.col("asked").alias("round"), F.coalesce("depth", F.lit(0)).cast("long").alias("depth"))


def depth_after(log: DataFrame, until: int, radius: float, p: BallPlan) -> DataFrame:
    """Sample depths after the log's rounds up to ``until``."""
    rows = log.where(F.col("round") <= until).select("x", "y", (F.col("w") * F.col("sign")).alias("dw"))
    return sample_depth(G.to_dual(rows, radius, ["x", "y"]).withColumnRenamed("dw", "w"), p).where("depth <> 0")


def epoch_stats(log: DataFrame, radius: float, p: BallPlan, budget: float | None = None) -> DataFrame:
    """(epoch, updates, resampled, touched): work of an epoch, the standing balls it starts with included."""
    rows = staged(with_epochs(log, assign_epochs(log)), "epoch-rows")
    fresh = {} if budget is None else {"t": epoch_samples(p.eps, budget), "seed": F.col("epoch")}
    # a round but an epoch's first has one ball, so its samples are counted where they are made; equal balls are counted once
    opening = rows.join(F.broadcast(rows_starts(rows)), "epoch")
    dual = lambda df, *keep: G.to_dual(df, radius, ["x", "y"]).select("epoch", "base", "c0", "c1", *keep)
    later = dual(opening.where("round > first").groupBy("epoch", "base", "x", "y").agg(F.count("*").alias("n")), "n")
    many = sample_hits(later, p, ["epoch", "n"], **fresh).groupBy("epoch").agg(F.sum("n").alias("touched"))
    first = dual(opening.where("round = first").select("epoch", "base", "x", "y").distinct())
    once = sample_hits(first, p, ["epoch"], **fresh).distinct().groupBy("epoch").agg(F.count("*").alias("touched"))
    touched = many.union(once).groupBy("epoch").agg(F.sum("touched").alias("touched"))
    sizes = rows.groupBy("epoch").agg(F.count("*").alias("rows"), F.countDistinct("round").alias("updates"))
    return sizes.join(touched, "epoch", "left").select("epoch", "updates", (F.col("rows") - F.col("updates")).alias("resampled"), F.coalesce("touched", F.lit(0)).alias("touched"))


def rows_starts(rows: DataFrame) -> DataFrame:
    """(epoch, first): the round of each epoch in which standing balls come in, its first."""
    return rows.groupBy("epoch").agg(F.min("round").alias("first"))
