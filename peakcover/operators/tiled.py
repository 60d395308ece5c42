"""Exact work around every disk, by tiles: a task holds a share of a tile's disks and all disks that these can meet.

Near pairs are made inside numpy and never become rows; what is shuffled is each disk a few times.  A tile of more
than ``SHARE`` disks is dealt into shares, each with all neighbours, so no pair is lost and no task holds all pairs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Disks of one share of a tile; sides of tiles and of the cells in which places are counted, in radii.
SHARE, SIDE, FINE = 256, 2.0, 0.25
#: Pairs handled at once.
PAIRS = 1 << 20
TOUCH = 1 + 3e-9


def around(disks: DataFrame, solve, schema: str, keep: list[str]) -> DataFrame:
    """``solve(x, y, own, frame)`` on every share: unit disks sorted by place, ``own`` marks those that are its to follow."""
    at = [F.floor(F.col(f"c{i}") / SIDE).cast("long") for i in range(2)]
    rows = disks.select("c0", "c1", *keep, at[0].alias("o0"), at[1].alias("o1"))
    many = rows.groupBy(F.col("o0").alias("t0"), F.col("o1").alias("t1")).agg(F.ceil(F.count("*") / F.lit(SHARE)).cast("long").alias("shares"))
    for i in range(2):
        rows = rows.withColumn(f"t{i}", F.explode(F.sequence(*(F.floor((F.col(f"c{i}") + s * (SIDE + 1e-6)) / SIDE).cast("long") for s in (-1, 1)))))
    rows = rows.join(many, ["t0", "t1"]).withColumn("share", F.explode(F.sequence(F.lit(0).cast("long"), F.col("shares") - 1)))
    own = (F.col("t0") == F.col("o0")) & (F.col("t1") == F.col("o1")) & (F.col("share") == F.pmod(F.xxhash64("c0", "c1"), F.col("shares")))
    rows = rows.select("t0", "t1", "share", "c0", "c1", *keep, own.alias("own"))

    def run(frame):
        import pandas as pd

        frame = frame.sort_values(["c0", "c1", *keep], ignore_index=True)
        mine = frame["own"].to_numpy(bool)
        found = solve(frame["c0"].to_numpy(), frame["c1"].to_numpy(), mine, frame) if mine.any() else None
        return pd.DataFrame([found] if found else [], columns=[c.split()[0] for c in schema.split(", ")])

    parts = 4 * int(disks.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # few bytes, much work: not to be coalesced
    return rows.repartition(parts, "t0", "t1", "share").groupBy("t0", "t1", "share").applyInPandas(run, schema)


def near(x, y, own):
    """Batches (i, j) of the pairs of a followed disk and another at most two radii away, small ones first."""
    import numpy as np

    step, at, size = max(1, PAIRS // max(1, len(x))), 0, 8
    while at < len(own):
        a = own[at : at + min(step, size)]
        at, size = at + len(a), 2 * size
        lo, hi = np.searchsorted(x, [x[a].min() - 2.001, x[a].max() + 2.001])  # disks are sorted by x
        i, j = np.nonzero((x[None, lo:hi] - x[a, None]) ** 2 + (y[None, lo:hi] - y[a, None]) ** 2 <= 4 * (1 + 1e-9))
        i, j = a[i], j + lo
        yield i[i != j], j[i != j]


def crossing_places(x, y, i, j):
    """The two places where circles i and j cross (one and the same where they touch)."""
    import numpy as np

    dx, dy = x[j] - x[i], y[j] - y[i]
    d2 = dx * dx + dy * dy
    h = np.sqrt(np.maximum(0.0, 1 - d2 / 4) / d2)
    mx, my = (x[i] + x[j]) / 2, (y[i] + y[j]) / 2
    return np.concatenate([mx - h * dy, mx + h * dy]), np.concatenate([my + h * dx, my - h * dx])


def deepest(px, py, x, y, value, coloured: bool):
    """(depth, x, y) of the deepest of the places: weights added up, or distinct colours; counted in small cells of places."""
    import numpy as np

    best = (0, 0.0, 0.0)
    if not len(px):
        return best
    k0, k1 = (np.floor(p / FINE).astype(np.int64) for p in (px, py))
    order = np.lexsort((py, px, k1, k0))
    px, py, k0, k1 = px[order], py[order], k0[order], k1[order]
    first = np.flatnonzero(np.append(True, (np.diff(k0) != 0) | (np.diff(k1) != 0)))
    reach = 1 + 1e-6 + FINE * 2**-0.5
    for at, end in zip(first, np.append(first[1:], len(px))):
        m0, m1 = (k0[at] + 0.5) * FINE, (k1[at] + 0.5) * FINE
        lo, hi = np.searchsorted(x, [m0 - reach, m0 + reach])
        seen = lo + np.flatnonzero((x[lo:hi] - m0) ** 2 + (y[lo:hi] - m1) ** 2 <= reach * reach)
        held = value[seen]
        if coloured:
            by = np.argsort(held, kind="stable")
            seen, starts = seen[by], np.unique(held[by], return_index=True)[1]
            if len(starts) <= best[0]:
                continue
        elif not len(seen) or held[held > 0].sum() <= best[0]:
            continue
        step = max(1, PAIRS // max(1, len(seen)))
        for b in range(at, end, step):
            qx, qy = px[b : min(end, b + step)], py[b : min(end, b + step)]
            inside = (x[seen] - qx[:, None]) ** 2 + (y[seen] - qy[:, None]) ** 2 <= TOUCH
            depth = np.logical_or.reduceat(inside, starts, axis=1).sum(axis=1) if coloured else inside @ value[seen]
            top = int(depth.argmax())
            if depth[top] > best[0]:
                best = (int(depth[top]), float(qx[top]), float(qy[top]))
    return best
