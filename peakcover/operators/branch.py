"""Exact optima by branch and bound: the deepest ball in space, the heaviest box in any dimension.

A node is a region of places.  What covers all of it is added up once and dropped, what meets none of it too, so a
node holds only the rows whose boundary passes through it; the weight of all that meet it bounds its places from
above, and a place inside from below.  Nodes that cannot pass the best place known are left out, the others halved.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Balls are closed, with this much room on the squared radius.
TOUCH = 1 + 1e-9
#: Spheres of a node whose crossings are tried at once; comparisons at which a box node is tried place by place.
FEW, TRIED = 12, 1 << 18
#: Disks of a node, or its half side, at which a method's own search of the node takes over; room around such a node.
LEAF, SMALL, ROOM = 64, 2.0**-10, 1e-6
#: Nodes that every cell opens before the best of all cells is shared; shares that a cell is then dealt into.
DIVE, SHARES = 100, 8


def added(w: np.ndarray) -> np.ndarray:
    """Weights in doubles where these add them up exactly."""
    return w.astype(np.float64) if float(np.abs(w).sum()) < 1 << 53 else w


def _tried(at: np.ndarray, w: np.ndarray, edges: list, sides: np.ndarray):
    """The most weight in a box with one of the lower edges on each axis."""
    held = [(at[:, i] >= e[:, None]) & (at[:, i] <= (e + sides[i])[:, None]) for i, e in enumerate(edges)]
    halves = []
    for part in (held[: len(held) // 2], held[len(held) // 2 :]):
        both = np.ones((1, len(w)), bool)
        for h in part:
            both = (both[:, None] & h[None]).reshape(-1, len(w))
        halves.append(both.astype(w.dtype))
    return (halves[0] * w @ halves[1].T).max()


def best_box(at: np.ndarray, own: np.ndarray, w: np.ndarray, sides, known=0, nodes: int | None = None):
    """The most weight in a box whose lower edges are coordinates of ``own`` rows, if above ``known``; the best of some ``nodes`` if given."""
    sides, w, best = np.asarray(sides, np.float64), added(w), known
    edges = [np.unique(at[own[:, i], i]) for i in range(len(sides))]
    if not all(map(len, edges)):
        return known
    stack = [(w.sum(), 0, np.arange(len(w)), edges)]
    while stack and nodes != 0:
        most, sure, rows, edges = stack.pop()
        if most <= best:
            continue
        nodes = None if nodes is None else nodes - 1
        if not len(rows):
            best = max(best, sure)
            continue
        p, held, sizes = at[rows], w[rows], [len(e) for e in edges]
        if max(sizes) == 1 or float(np.prod(np.array(sizes, np.float64))) * len(rows) <= TRIED:
            best = max(best, sure + _tried(p, held, edges, sides))
            continue
        low = np.array([e[n // 2] for e, n in zip(edges, sizes)])
        best = max(best, sure + held[((p >= low) & (p <= low + sides)).all(1)].sum())
        axis = int(np.argmax(sizes))
        parts = []
        for part in np.split(edges[axis], [sizes[axis] // 2]):
            meets = (p[:, axis] >= part[0]) & (p[:, axis] <= part[-1] + sides[axis])
            most = sure + held[meets].sum()
            if most <= best:
                continue
            q, mine = p[meets], list(edges)
            mine[axis] = part
            first, last = (np.array([e[k] for e in mine]) for k in (0, -1))
            whole = ((q >= last) & (q <= first + sides)).all(1)
            # a lower edge is a coordinate of a row that meets the node; rows dropped before can only be at the last edge
            mine = [np.append(e[:-1][np.isin(e[:-1], q[:, i])], e[-1]) for i, e in enumerate(mine)]
            parts.append((most, sure + held[meets][whole].sum(), rows[meets][~whole], mine))
        stack.extend(sorted(parts, key=lambda t: t[0]))
    return best


def _crossings(p: np.ndarray, radius: float) -> np.ndarray:
    """Of a few spheres the lowest places on the first axis: of each, of each two's circle, and the crossings of three."""
    found = [p - np.array([radius, 0, 0])]
    below = np.tri(len(p), len(p), -1, bool)
    i, j = np.nonzero(below)
    v = p[j] - p[i]
    d2 = (v * v).sum(1)
    met = (d2 > 0) & (d2 <= 4 * radius * radius * TOUCH)
    i, j, v, d2 = i[met], j[met], v[met], d2[met]
    down = -v[:, :1] * -v / d2[:, None] - np.array([1.0, 0, 0])  # the first axis turned down, in the plane of the circle
    long = np.sqrt((down * down).sum(1))[:, None]
    found.append((p[i] + p[j]) / 2 + down / np.where(long > 0, long, 1) * np.sqrt(np.maximum(0, radius * radius - d2 / 4))[:, None])
    i, j, k = np.nonzero(below[:, :, None] & below[None])
    a, u, v = p[i], p[j] - p[i], p[k] - p[i]
    n = np.cross(u, v)
    nn = (n * n).sum(1)
    ok = nn > 0
    a, u, v, n, nn = a[ok], u[ok], v[ok], n[ok], nn[ok]
    out = (np.cross(n, u) * (v * v).sum(1)[:, None] + np.cross(v, n) * (u * u).sum(1)[:, None]) / (2 * nn)[:, None]
    rest = radius * radius - (out * out).sum(1)
    ok = rest >= -1e-9 * radius * radius
    step = n[ok] * np.sqrt(np.maximum(rest[ok], 0) / nn[ok])[:, None]
    return np.concatenate([*found, a[ok] + out[ok] + step, a[ok] + out[ok] - step])


def best_ball(p: np.ndarray, w: np.ndarray, radius: float, centre, half: float, known=0, nodes: int | None = None):
    """The most weight in a closed ball with its centre in the cube, if above ``known``; the best of some ``nodes`` if given.

    The balls that hold an optimal place share a lowest place, where at most three of their spheres meet; so in a small
    cube with few spheres these places are tried.  A cube below the room on the radius is settled by its centre.
    """
    best, reach, w = known, radius * radius * TOUCH, added(w)
    stack = [(w.sum(), 0, np.arange(len(w)), np.asarray(centre, np.float64), half)]
    while stack and nodes != 0:
        most, sure, rows, c, h = stack.pop()
        if most <= best:
            continue
        nodes = None if nodes is None else nodes - 1
        if not len(rows):
            best = max(best, sure)
            continue
        q, held = p[rows], w[rows]
        if len(rows) <= FEW and h < radius / 8:
            places = _crossings(q, radius)
            places = places[(np.abs(places - c) <= h + 1e-6 * radius).all(1)]
            if len(places):
                best = max(best, sure + ((((places[:, None] - q) ** 2).sum(2) <= reach) @ held).max())
            continue
        h /= 2
        off = [np.abs(q[:, i] - (c[i] + np.array([[-h], [h]]))) for i in range(3)]
        eight = lambda f: (f[0][:, None, None] + f[1][None, :, None] + f[2][None, None]).reshape(8, -1)
        meets, whole = eight([np.maximum(t - h, 0) ** 2 for t in off]) <= reach, eight([(t + h) ** 2 for t in off]) <= reach
        best = max(best, sure + ((eight([t * t for t in off]) <= reach) @ held).max())
        if h <= 1e-10 * radius:
            continue
        most = sure + meets @ held
        for k in np.argsort(most, kind="stable"):
            if most[k] > best:
                side = np.array([k >> 2 & 1, k >> 1 & 1, k & 1])
                stack.append((most[k], sure + held[whole[k]].sum(), rows[meets[k] & ~whole[k]], c + h * (2 * side - 1), h))
    return best


def best_of_cells(rows: DataFrame, keys: list[str], known, solve, kind: str, most: int | None = None):
    """The best of all cells of (keys.., w, ..) from ``known`` on: every cell opens some nodes, then those that may still pass the best are settled.

    ``solve(frame, key, known, share, nodes)`` settles one of ``SHARES`` parts of a cell, or opens ``nodes`` of all (share None).
    """
    from ..plans.staging import staged

    rows = staged(rows, "branch-rows")
    held = staged(rows.groupBy(*keys).agg(F.sum("w").alias("held")), "branch-cells")
    parts = 4 * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # few bytes, much work: not to be coalesced

    def run(share: bool, known):
        import pandas as pd

        def work(key, frame):
            if most is not None and len(frame) > most:
                raise ValueError(f"a cell holds {len(frame)} points, more than {most}")
            return pd.DataFrame({"weight": [solve(frame, key[: len(keys)], known, int(key[-1]) if share else None, None if share else DIVE)]})

        met = rows.join(held.where(F.col("held") > F.lit(known)).select(*keys), keys, "left_semi")
        by = keys
        if share:
            met, by = met.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(SHARES - 1)))), [*keys, "share"]
        return max(known, met.repartition(parts, *by).groupBy(*by).applyInPandas(work, f"weight {kind}").agg(F.max("weight")).first()[0] or 0)

    return run(True, run(False, known))


def most_colours(x: np.ndarray, y: np.ndarray, hue: np.ndarray, centre, half: float, known: int = 0, nodes: int | None = None, leaf=None):
    """(colours, x, y) of the place in a square that closed unit disks of most colours cover, (known, nan, nan) if that is not passed.

    A colour that covers all of a node is counted once and dropped with all its disks.  With ``leaf`` no centres of nodes are
    tried: ``leaf(x, y, hue, node)`` finds the best place of a small node with the disks that are left, all of whose circles
    pass through it; what it holds of the colours dropped is added.
    """
    reach, best, room = 1 + 2e-9, (known, float("nan"), float("nan")), ROOM if leaf else 0.0
    order = np.argsort(hue, kind="stable")
    x, y, hue = x[order], y[order], hue[order]
    stack = [(len(np.unique(hue)), 0, np.arange(len(x)), float(centre[0]), float(centre[1]), half)]
    while stack and nodes != 0:
        most, sure, rows, c0, c1, h = stack.pop()
        if most <= best[0]:
            continue
        if not len(rows):
            best = (sure, c0, c1)
            continue
        nodes = None if nodes is None else nodes - 1
        if leaf and (len(rows) <= LEAF or h <= SMALL):
            found = leaf(x[rows], y[rows], hue[rows], (c0, c1, h + ROOM)) or (0, c0, c1)
            best = (sure + found[0], *found[1:]) if sure + found[0] > best[0] else best
            continue
        h /= 2
        fresh = np.append(True, np.diff(hue[rows]) != 0)
        starts, which = np.flatnonzero(fresh), np.cumsum(fresh) - 1
        off = [np.abs(v[rows] - (c + np.array([[-h], [h]]))) for v, c in ((x, c0), (y, c1))]
        four = lambda f: (f[0][:, None] + f[1][None]).reshape(4, -1) <= reach
        colours = lambda m: np.logical_or.reduceat(m, starts, axis=1)
        meets = four([np.maximum(t - h - room, 0) ** 2 for t in off])
        whole = colours(four([(t + h + room) ** 2 for t in off]))
        places = [(c0 + h * (2 * (k >> 1) - 1), c1 + h * (2 * (k & 1) - 1)) for k in range(4)]
        if not leaf:
            depth = sure + colours(four([t * t for t in off])).sum(axis=1)
            top = int(depth.argmax())
            if depth[top] > best[0]:
                best = (int(depth[top]), *places[top])
        if h <= 1e-10:
            continue
        most = sure + colours(meets).sum(axis=1)
        for k in np.argsort(most, kind="stable"):
            if most[k] > best[0]:
                stack.append((int(most[k]), sure + int(whole[k].sum()), rows[meets[k] & ~whole[k][which]], *places[k], h))
    return best
