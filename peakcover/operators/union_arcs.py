"""Boundaries of the unions of same-coloured disks, and exact coloured placement by sweeping along them.

Disks are closed, of one radius, and collapsed by place and colour.  A colour's boundary consists of the arcs
of its circles that no other disk of the colour covers.  The most colours over one point are met on such an
arc: moving inside the deepest face until a region would be left stops on a boundary with nothing lost.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import cell_kernels as kernels
from . import tiled
from .colored_disk import by_branches
from .exact_disk import TURN, WIDEN, neighbours

THIN = 1e-9


def disks_of(points: DataFrame, color: str = "color") -> DataFrame:
    """(id, x, y, hue): one disk for each place and colour."""
    return points.groupBy(F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), F.col(color).alias("hue")).agg(F.min("id").alias("id"))


def covered(disks: DataFrame, radius: float, same: bool, widen: float) -> DataFrame:
    """(i, hue, other, x, y, lo, hi): angles of disk i that disks of its own (or each other) colour cover, cut at 2 pi."""
    d = disks.withColumn("id", F.xxhash64("id", "hue"))
    near = neighbours(d, radius, ["hue"]).withColumnRenamed("own_hue", "mine")
    near = near.where("mine = hue AND D > 0" if same else "mine <> hue")
    half = F.when(F.col("D") == 0, F.lit(math.pi)).otherwise(F.acos(F.least(F.lit(1.0), F.col("D") / (2 * radius))) + widen)
    lo = F.when(F.col("D") == 0, F.lit(0.0)).otherwise(F.pmod(F.atan2(F.col("y2") - F.col("y"), F.col("x2") - F.col("x")) - half, F.lit(TURN)))
    cut = F.expr(f"if(hi > {TURN!r}D, array(named_struct('lo', lo, 'hi', {TURN!r}D), named_struct('lo', 0D, 'hi', hi - {TURN!r}D)), array(named_struct('lo', lo, 'hi', hi)))")
    return near.withColumn("lo", lo).withColumn("hi", F.col("lo") + 2 * half).withColumn("part", F.explode(cut)).select("i", F.col("mine").alias("hue"), F.col("hue").alias("other"), "x", "y", "part.lo", "part.hi")


def islands(spans: DataFrame, keys: list[str], gap: float = 0.0) -> DataFrame:
    """Overlapping spans (lo, hi) of the same keys merged."""
    before = Window.partitionBy(*keys).orderBy("lo", "hi").rowsBetween(Window.unboundedPreceding, -1)
    upto = Window.partitionBy(*keys).orderBy("lo", "hi").rowsBetween(Window.unboundedPreceding, 0)
    marked = spans.withColumn("reach", F.max("hi").over(before)).withColumn("fresh", F.expr(f"if(reach IS NULL OR lo > reach + {gap}D, 1, 0)")).withColumn("island", F.sum("fresh").over(upto))
    return marked.groupBy(*keys, "island").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).drop("island")


def union_arcs(disks: DataFrame, radius: float) -> DataFrame:
    """(i, hue, x, y, lo, hi): the exposed arcs of every disk, as angles from 0 to 2 pi."""
    d = disks.withColumn("i", F.xxhash64("id", "hue")).select("i", "hue", "x", "y")
    merged = islands(covered(disks, radius, True, 0.0).select("i", "lo", "hi"), ["i"], THIN)
    ends = merged.union(d.select("i", F.lit(TURN).alias("lo"), F.lit(TURN).alias("hi")))
    before = Window.partitionBy("i").orderBy("lo", "hi").rowsBetween(Window.unboundedPreceding, -1)
    gaps = ends.withColumn("from", F.coalesce(F.max("hi").over(before), F.lit(0.0))).where(F.col("lo") - F.col("from") > THIN).select("i", F.col("from").alias("lo"), F.col("lo").alias("hi"))
    return gaps.join(d, "i").select("i", "hue", "x", "y", "lo", "hi")


def monotone_arcs(arcs: DataFrame) -> DataFrame:
    """The arcs cut where a circle turns in x: (.., lo, hi, upper); with the cut at angle 0 an arc gives three at most."""
    pieces = F.array(F.struct("lo", F.least("hi", F.lit(math.pi)).alias("hi"), F.lit(True).alias("upper")), F.struct(F.greatest("lo", F.lit(math.pi)).alias("lo"), F.col("hi"), F.lit(False).alias("upper")))
    return arcs.withColumn("piece", F.explode(pieces)).where(F.col("piece.hi") > F.col("piece.lo")).select("i", "hue", "x", "y", "piece.lo", "piece.hi", "piece.upper")


def sweep(spans: DataFrame, keys: list[str], radius: float) -> DataFrame:
    """(keys.., x, y, depth): 1 + the most spans over one angle, starts before ends."""
    ends = spans.select(*keys, "x", "y", F.explode(F.array(F.struct(F.col("lo").alias("at"), F.lit(0).alias("kind"), F.lit(1).alias("d")), F.struct(F.col("hi").alias("at"), F.lit(1).alias("kind"), F.lit(-1).alias("d")))).alias("e")).select(*keys, "x", "y", "e.*")
    run = Window.partitionBy(*keys).orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    best = ends.withColumn("depth", F.sum("d").over(run) + 1).groupBy(*keys).agg(F.max(F.struct("depth", "at", "x", "y")).alias("b"))
    return best.select(*keys, (F.col("b.x") + radius * F.cos("b.at")).alias("x"), (F.col("b.y") + radius * F.sin("b.at")).alias("y"), F.col("b.depth").cast("long").alias("depth"))


def deepest_place(found: DataFrame, disks: DataFrame) -> DataFrame:
    """The best row, or any disk's own centre with depth 1 where no two colours meet."""
    alone = disks.select("x", "y", F.lit(1).cast("long").alias("depth"))
    return found.select("x", "y", "depth").union(alone).orderBy(F.desc("depth"), "x", "y").limit(1)


def unit_disks(points: DataFrame, radius: float, color: str) -> DataFrame:
    """(c0, c1, hue): the disks of ``disks_of`` that have a colour, as unit disks."""
    return points.where(F.col(color).isNotNull()).select(*((F.col(c).cast("double") / radius).alias(n) for c, n in (("x", "c0"), ("y", "c1"))), F.col(color).alias("hue")).distinct()


def other_islands(x, y, hue, i, j):
    """(circle, lo, hi): around each circle i every other colour's merged angles, of the pairs given."""
    import numpy as np

    i, j = i[hue[i] != hue[j]], j[hue[i] != hue[j]]
    lo, hi, which = kernels.covered(x[j] - x[i], y[j] - y[i], WIDEN)
    circle, rank = np.unique(i, return_inverse=True)
    colours = int(hue.max()) + 1
    key, lo, hi = kernels.merged(rank[which] * colours + hue[j[which]], lo, hi)
    return circle[key // colours], lo, hi


def most_spans(key, lo, hi, place=None):
    """(depth, angle, key): 1 + the most spans over one angle of one key, starts before ends; ``place(key, angle)`` tells which starts count."""
    import numpy as np

    angle, kind, keys = np.concatenate([lo, hi]), np.repeat([0, 1], len(lo)), np.tile(key, 2)
    turn = np.lexsort((kind, angle, keys))
    depth = 1 + np.cumsum(1 - 2 * kind[turn])
    if place is not None:
        depth = np.where((kind[turn] == 0) & place(keys[turn], angle[turn]), depth, 0)
    top = int(depth.argmax())
    return int(depth[top]), angle[turn[top]], keys[turn[top]]


def own_arcs(x, y, hue, own, pairs):
    """Arrays (disk, lo, hi): the arcs of these circles that no other disk of the colour covers, of the pairs given."""
    import numpy as np

    owners, los, his = [own, own], [np.full(len(own), -1.0), np.full(len(own), TURN)], [np.zeros(len(own)), np.full(len(own), TURN + 1)]
    for i, j in pairs:
        i, j = i[hue[i] == hue[j]], j[hue[i] == hue[j]]
        lo, hi, which = kernels.covered(x[j] - x[i], y[j] - y[i])
        owners.append(i[which])
        los.append(lo)
        his.append(hi)
    owner, lo, hi = kernels.merged(np.concatenate(owners), np.concatenate(los), np.concatenate(his))
    gap = (owner[1:] == owner[:-1]) & (lo[1:] - hi[:-1] > THIN)
    return owner[:-1][gap], hi[:-1][gap], lo[1:][gap]


def coloured_by_circles(points: DataFrame, radius: float, color: str = "color") -> DataFrame:
    """The straightforward exact method: around every circle, all other colours' islands."""

    def solve(x, y, mine, frame):
        import numpy as np
        import pandas as pd

        hue, own, best = pd.factorize(frame["hue"])[0], np.flatnonzero(mine), None
        for i, j in tiled.near(x, y, own):
            if not (hue[i] != hue[j]).any():
                continue
            circle, lo, hi = other_islands(x, y, hue, i, j)
            depth, turn, c = most_spans(circle, lo, hi)
            if best is None or depth > best[0]:
                best = (depth, float(x[c] + math.cos(turn)) * radius, float(y[c] + math.sin(turn)) * radius)
                if depth > hue.max():  # all colours that the share knows: no place has more
                    break
        return best

    found = tiled.around(unit_disks(points, radius, color), solve, "depth long, x double, y double", ["hue"])
    return deepest_place(found, disks_of(points, color))


def node_pairs(x, y):
    """Batches (own, i, j) of a node's disks and the pairs of one of them and another at most two radii away."""
    import numpy as np

    step = max(1, kernels.PAIRS // max(1, len(x)))
    for at in range(0, len(x), step):
        own = np.arange(at, min(at + step, len(x)))
        i, j = np.nonzero((x[own, None] - x[None]) ** 2 + (y[own, None] - y[None]) ** 2 <= 4 * (1 + 1e-9))
        i = own[i]
        yield own, i[i != j], j[i != j]


def within(px, py, node):
    import numpy as np

    return (np.abs(px - node[0]) <= node[2]) & (np.abs(py - node[1]) <= node[2])


def swept_arcs(x, y, hue, node):
    """(depth, x, y) of the best place in a node by sweeps along the exposed arcs in it, each other colour's islands clipped to the arc."""
    import numpy as np

    best = None
    for own, i, j in node_pairs(x, y):
        disk, first, last = own_arcs(x, y, hue, own, [(i, j)])
        circle, lo, hi = other_islands(x, y, hue, i, j) if (hue[i] != hue[j]).any() else (i[:0], first[:0], first[:0])
        # every island of a circle with every arc of it
        at = np.searchsorted(disk, circle)
        n = np.searchsorted(disk, circle, "right") - at
        island = np.repeat(np.arange(len(n)), n)
        arc = np.repeat(at - np.append(0, np.cumsum(n)[:-1])[: len(n)], n) + np.arange(n.sum())
        met = (hi[island] >= first[arc]) & (lo[island] <= last[arc])
        island, arc = island[met], arc[met]
        # the arc's own colour is a span over all of it
        lo, hi = np.append(np.maximum(lo[island], first[arc]), first), np.append(np.minimum(hi[island], last[arc]), last)
        if not len(lo):
            continue
        where = lambda k, turn: within(x[disk[k]] + np.cos(turn), y[disk[k]] + np.sin(turn), node)
        depth, turn, k = most_spans(np.append(arc, np.arange(len(disk))), lo, hi, where)
        if depth and (best is None or depth - 1 > best[0]):
            best = (depth - 1, float(x[disk[k]] + math.cos(turn)), float(y[disk[k]] + math.sin(turn)))
    return best


def coloured_arc_sweep(points: DataFrame, radius: float, color: str = "color") -> DataFrame:
    """The same along exposed arcs only: each other colour's islands are clipped to the arc.

    The plane is halved into nodes; a colour that covers all of a node is counted and needs no arcs there, and nodes that
    cannot pass the best place known are left out.  In the others all arcs are swept.
    """
    return deepest_place(by_branches(points, radius, color, swept_arcs), disks_of(points, color))


def arc_crossings(points: DataFrame, radius: float, color: str = "color") -> DataFrame:
    """(i, o, hue, other, x, y): places where exposed arcs of different colours cross, each once."""
    disks = disks_of(points, color)
    arcs = union_arcs(disks, radius)
    d = disks.withColumn("id", F.xxhash64("id", "hue"))
    near = neighbours(d, radius, ["hue"]).withColumnRenamed("own_hue", "mine").where("mine <> hue AND D > 0 AND i < o")
    half, middle = F.acos(F.least(F.lit(1.0), F.col("D") / (2 * radius))), F.atan2(F.col("y2") - F.col("y"), F.col("x2") - F.col("x"))
    sides = near.withColumn("side", F.explode(F.array(F.lit(-1.0), F.lit(1.0)))).where("side > 0 OR D < " + repr(2 * radius * (1 - 1e-12)) + "D")
    at = sides.withColumn("ai", F.pmod(middle + F.col("side") * half, F.lit(TURN))).withColumn("ao", F.pmod(middle + math.pi - F.col("side") * half, F.lit(TURN)))
    mine = arcs.select("i", F.col("lo").alias("l1"), F.col("hi").alias("h1"))
    theirs = arcs.select(F.col("i").alias("o"), F.col("lo").alias("l2"), F.col("hi").alias("h2"))
    inside = lambda a, lo, hi: f"({a} BETWEEN {lo} - {WIDEN}D AND {hi} + {WIDEN}D OR {a} + {TURN!r}D BETWEEN {lo} - {WIDEN}D AND {hi} + {WIDEN}D OR {a} - {TURN!r}D BETWEEN {lo} - {WIDEN}D AND {hi} + {WIDEN}D)"
    met = at.join(mine, "i").where(inside("ai", "l1", "h1")).join(theirs, "o").where(inside("ao", "l2", "h2"))
    place = met.select("i", "o", "side", F.col("mine").alias("hue"), F.col("hue").alias("other"), (F.col("x") + radius * F.cos("ai")).alias("x"), (F.col("y") + radius * F.sin("ai")).alias("y"))
    return place.dropDuplicates(["i", "o", "side"])


def crossed_arcs(x, y, hue, node):
    """(depth, x, y) of the best of a node's candidates: the starts of exposed arcs in it, and the crossings of two colours' arcs."""
    import numpy as np

    order = np.lexsort((y, x))
    x, y, hue = x[order], y[order], hue[order]
    disk, lo, hi = own_arcs(x, y, hue, np.arange(len(x)), (p[1:] for p in node_pairs(x, y)))
    starts, ends = lo + kernels.APART * disk, hi + kernels.APART * disk

    def on_arc(i, px, py):
        turn = np.mod(np.arctan2(py - y[i], px - x[i]), TURN)
        ok = np.zeros(len(i), dtype=bool)
        for full in (0.0, TURN, -TURN):
            k = np.searchsorted(starts, turn + full + WIDEN + kernels.APART * i, "right") - 1
            ok |= (k >= 0) & (disk[k] == i) & (ends[k] >= turn + full - WIDEN + kernels.APART * i)
        return ok

    px, py = x[disk] + np.cos(lo), y[disk] + np.sin(lo)
    ok = within(px, py, node)
    best = tiled.deepest(px[ok], py[ok], x, y, hue, True)
    if not len(disk):  # all circles are covered here
        return None
    for _, i, j in node_pairs(x, y):
        apart = (hue[i] != hue[j]) & ((x[i] != x[j]) | (y[i] != y[j])) & (i < j)
        px, py = tiled.crossing_places(x, y, i[apart], j[apart])
        i, j = np.tile(i[apart], 2), np.tile(j[apart], 2)
        ok = within(px, py, node)
        i, j, px, py = i[ok], j[ok], px[ok], py[ok]
        ok = on_arc(i, px, py) & on_arc(j, px, py)
        best = max(best, tiled.deepest(px[ok], py[ok], x, y, hue, True), key=lambda b: b[0])
    return best if best[0] else None


def coloured_by_crossings(points: DataFrame, radius: float, color: str = "color") -> DataFrame:
    """The form whose work follows the number of crossings: they and one start for each arc are the candidates.

    In nodes as in ``coloured_arc_sweep``: crossings are made where some place may still pass the best known.
    """
    return deepest_place(by_branches(points, radius, color, crossed_arcs), disks_of(points, color))
