"""Exact coloured placement inside one group of unit disks, in numpy: angular sweep, slabs, and a trapezoidal map.

A group holds the disks of one grid cell, or of one vertical strip.  Every kernel returns (depth, x, y) with the
depth counted directly at the place returned, so a degenerate arrangement can never make it report too much.
Slabs and trapezoids find the deepest face; the only places counted besides are pinches, where a closed optimum
may be a single point: touching circles, and crossings that fall together.
"""

from __future__ import annotations

import math
from collections import deque

TOL = 1e-9
WIDEN = 1e-7
PINCH = 1e-6
TURN = 2 * math.pi
#: Apart by more than a turn: what belongs to different owners never overlaps once shifted.
APART = 10.0
#: Pairs, and slab entries, handled at once.
PAIRS, ENTRIES = 1 << 20, 1 << 20


def depth_of(px, py, x, y, hue):
    """Distinct colours over each place."""
    import numpy as np

    near = (px[:, None] - x) ** 2 + (py[:, None] - y) ** 2 <= 1 + 1e-8
    order = np.argsort(hue, kind="stable")
    starts = np.unique(hue[order], return_index=True)[1]
    return np.logical_or.reduceat(near[:, order], starts, axis=1).sum(axis=1) if len(x) else np.zeros(len(px), np.int64)


def best_of(px, py, x, y, hue):
    import numpy as np

    best = (0, 0.0, 0.0)
    step = max(1, PAIRS // max(1, len(x)))
    for at in range(0, len(px), step):
        d = depth_of(px[at : at + step], py[at : at + step], x, y, hue)
        i = int(np.argmax(d))
        if d[i] > best[0]:
            best = (int(d[i]), float(px[at + i]), float(py[at + i]))
    return best


def covered(dx, dy, widen: float = 0.0):
    """(lo, hi, which): the angles of a unit circle that unit disks at these offsets cover, cut at a full turn."""
    import numpy as np

    dist = np.hypot(dx, dy)
    half = np.where(dist == 0, math.pi, np.arccos(np.minimum(1, dist / 2)) + widen)
    lo = np.where(dist == 0, 0.0, np.mod(np.arctan2(dy, dx) - half, TURN))
    hi = lo + 2 * half
    which = np.arange(len(lo))
    over = hi > TURN
    return np.concatenate([lo, np.zeros(over.sum())]), np.concatenate([np.minimum(hi, TURN), hi[over] - TURN]), np.concatenate([which, which[over]])


def merged(owner, lo, hi):
    """(owner, lo, hi) of the islands that overlapping spans of one owner form, in order."""
    import numpy as np

    order = np.lexsort((lo, owner))
    owner, lo, hi = owner[order], lo[order], hi[order]
    reach = np.maximum.accumulate(hi + APART * owner)
    fresh = np.ones(len(lo), dtype=bool)
    fresh[1:] = (lo + APART * owner)[1:] > reach[:-1]
    first = np.flatnonzero(fresh)
    last = np.append(first[1:], len(lo)) - 1
    return owner[first], lo[first], reach[last] - APART * owner[first]


def exposed(x, y, hue):
    """Arrays (disk, lo, hi) of the arcs that no other disk of the colour covers, by disk and angle."""
    import numpy as np

    n = len(x)
    owners, los, his = [np.arange(n), np.arange(n)], [np.full(n, -1.0), np.full(n, TURN)], [np.zeros(n), np.full(n, TURN + 1)]
    step = max(1, PAIRS // max(1, n))
    for at in range(0, n, step):
        dx, dy = x[None] - x[at : at + step, None], y[None] - y[at : at + step, None]
        d2 = dx * dx + dy * dy
        i, j = np.nonzero((hue[at : at + step, None] == hue[None]) & (d2 > 0) & (d2 <= 4))
        lo, hi, which = covered(dx[i, j], dy[i, j])
        owners.append(i[which] + at)
        los.append(lo)
        his.append(hi)
    owner, lo, hi = merged(np.concatenate(owners), np.concatenate(los), np.concatenate(his))
    gap = (owner[1:] == owner[:-1]) & (lo[1:] - hi[:-1] > TOL)
    return owner[:-1][gap], hi[:-1][gap], lo[1:][gap]


def crossings(x, y, hue, arcs):
    """(x, y, touching) of the places where exposed arcs of different colours meet, each pair of circles twice at most."""
    import numpy as np

    disk, lo, hi = arcs
    starts, ends = lo + APART * disk, hi + APART * disk

    def on_arc(i, px, py):
        at = np.mod(np.arctan2(py - y[i], px - x[i]), TURN) + APART * i
        k = np.searchsorted(starts, at + WIDEN) - 1
        return (k >= 0) & (ends[k] >= at - WIDEN) | (at - APART * i < WIDEN) | (at - APART * i > TURN - WIDEN)

    own = np.unique(disk)
    xs, ys, touch = [], [], []
    step = max(1, PAIRS // max(1, len(own)))
    for at in range(0, len(own), step):
        a = own[at : at + step]
        dx, dy = x[own][None] - x[a][:, None], y[own][None] - y[a][:, None]
        d2 = dx * dx + dy * dy
        i, j = np.nonzero((hue[a][:, None] != hue[own][None]) & (a[:, None] < own[None]) & (d2 > 0) & (d2 <= 4 * (1 + TOL)))
        dx, dy, d2, i, j = dx[i, j], dy[i, j], d2[i, j], a[i], own[j]
        h = np.sqrt(np.maximum(0, 1 - d2 / 4) / d2)
        for s in (-1, 1):
            px, py = x[i] + dx / 2 - s * h * dy, y[i] + dy / 2 + s * h * dx
            ok = on_arc(i, px, py) & on_arc(j, px, py)
            xs.append(px[ok])
            ys.append(py[ok])
            touch.append(d2[ok] >= 4 * (1 - 1e-7))
    return np.concatenate(xs or [np.zeros(0)]), np.concatenate(ys or [np.zeros(0)]), np.concatenate(touch or [np.zeros(0, bool)])


def pinches(px, py, touching):
    """The touching places, and of crossings that fall together one each."""
    import numpy as np

    together = np.zeros(len(px), dtype=bool)
    for shift in (0.0, 0.5):
        cells = np.floor(np.stack([px, py]) / PINCH + shift).astype(np.int64)
        _, back, count = np.unique(cells, axis=1, return_inverse=True, return_counts=True)
        together |= count[back.ravel()] > 1
    keep = np.flatnonzero(together | touching)
    if len(keep):
        keep = keep[np.unique(np.round(np.stack([px, py])[:, keep] / PINCH).astype(np.int64), axis=1, return_index=True)[1]]
    return px[keep], py[keep]


def sweep_kernel(x, y, hue, floor: int = 0, centre=None, near: float = math.inf):
    """Around each circle the other colours' covered angles are merged and counted, all circles of a batch side by side.

    Circles that most colours come near go first; the rest is skipped once none can pass the best, or ``floor``.
    With a centre only circles that come within ``near`` of it are followed.
    """
    import numpy as np

    n = len(x)
    if not n:
        return 0, 0.0, 0.0
    _, hue = np.unique(hue, return_inverse=True)
    colours = int(hue.max()) + 1
    step = max(1, PAIRS // n)
    limit = np.ones(n, dtype=np.int64)
    by_colour = np.argsort(hue, kind="stable")
    starts = np.searchsorted(hue[by_colour], np.arange(colours))
    for at in range(0, n, step):
        meets = (x[at : at + step, None] - x[by_colour]) ** 2 + (y[at : at + step, None] - y[by_colour]) ** 2 <= 4 * (1 + 2 * TOL)
        limit[at : at + step] = np.logical_or.reduceat(meets, starts, axis=1).sum(axis=1)
    if centre is not None:
        limit[np.abs(np.hypot(x - centre[0], y - centre[1]) - 1) > near] = 0
    best = (1, float(x[0]), float(y[0]))
    order = np.argsort(-limit, kind="stable")
    at, size = 0, 8
    while at < n and limit[order[at]] > max(best[0], floor):
        own = order[at : at + size]
        at, size = at + size, min(step, 2 * size)
        dx, dy = x[None] - x[own, None], y[None] - y[own, None]
        i, j = np.nonzero((hue[own, None] != hue[None]) & (dx * dx + dy * dy <= 4 * (1 + 2 * TOL)))
        if not len(i):
            continue
        lo, hi, which = covered(dx[i, j], dy[i, j], WIDEN)
        key, lo, hi = merged(i[which] * colours + hue[j[which]], lo, hi)
        circle = np.tile(key // colours, 2)
        angle, kind = np.concatenate([lo, hi]), np.repeat([0, 1], len(lo))
        turn = np.lexsort((kind, angle, circle))
        depth = 1 + np.cumsum(1 - 2 * kind[turn])
        top = int(depth.argmax())
        if depth[top] > best[0]:
            k, t = own[circle[turn[top]]], angle[turn[top]]
            best = (int(depth[top]), float(x[k] + math.cos(t)), float(y[k] + math.sin(t)))
    return best


def pieces_of(x, y, arcs):
    """(disk, upper, left, right): the arcs cut where a circle turns in x."""
    import numpy as np

    disk, lo, hi = arcs
    up, down = lo < math.pi, hi > math.pi
    a = np.concatenate([lo[up], np.maximum(lo[down], math.pi)])
    b = np.concatenate([np.minimum(hi[up], math.pi), hi[down]])
    d = np.concatenate([disk[up], disk[down]])
    upper = np.arange(len(d)) < up.sum()
    ends = np.sort(np.stack([x[d] + np.cos(a), x[d] + np.cos(b)]), axis=0)
    return d, upper, ends[0], ends[1]


def heights(at, x, y, disk, upper):
    import numpy as np

    rise = np.sqrt(np.maximum(0, 1 - (at - x[disk]) ** 2))
    return y[disk] + np.where(upper, rise, -rise)


def slab_order(x, y, hue, left: float = -math.inf, right: float = math.inf):
    """(disk, upper, crossing places, generator of (slab's left, right, pieces from below)) between two verticals."""
    import numpy as np

    arcs = exposed(x, y, hue)
    disk, upper, begin, end = pieces_of(x, y, arcs)
    met = crossings(x, y, hue, arcs)
    cuts = np.concatenate([begin, end, met[0], [left, right]])
    cuts = np.unique(cuts[np.isfinite(cuts) & (cuts >= left) & (cuts <= right)])
    if len(cuts):
        cuts = cuts[np.concatenate([[True], np.diff(cuts) > TOL])]

    def slabs():
        step = max(1, ENTRIES // max(1, len(disk)))
        for at in range(0, len(cuts) - 1, step):
            a, b = cuts[at : at + step + 1][:-1], cuts[at : at + step + 1][1:]
            h = heights(((a + b) / 2)[:, None], x, y, disk, upper)
            h[(begin > a[:, None] + TOL) | (end < b[:, None] - TOL)] = np.inf
            order = np.lexsort((np.broadcast_to(upper, h.shape), h), axis=1)
            count = np.isfinite(h).sum(axis=1)
            for k in range(len(a)):
                yield float(a[k]), float(b[k]), order[k, : count[k]], h[k]

    return disk, upper, met, slabs()


def strip(centre, near: float) -> tuple[float, float]:
    return (-math.inf, math.inf) if centre is None else (centre[0] - near, centre[0] + near)


def slab_kernel(x, y, hue, floor: int = 0, centre=None, near: float = math.inf):
    """The running sum of entered and left unions up each slab, in the strip around a centre if one is given."""
    import numpy as np

    left, right = strip(centre, near)
    disk, upper, met, slabs = slab_order(x, y, hue, left, right)
    sign, top, px, py = np.where(upper, -1, 1), 0, [], []
    for a, b, over, h in slabs:
        if len(over) < 2:
            continue
        depth = np.cumsum(sign[over])
        k = int(np.argmax(depth[:-1]))
        if depth[k] > top:
            top = int(depth[k])
            px.append((a + b) / 2)
            py.append((h[over[k]] + h[over[k + 1]]) / 2)
    return with_pinches(px[-1:], py[-1:], met, x, y, hue, left, right)


def with_pinches(px, py, met, x, y, hue, left: float, right: float):
    """The best of the deepest face's place and the pinches between the verticals; the first disk's centre if there is none."""
    import numpy as np

    vx, vy = pinches(*met)
    ok = (vx >= left) & (vx <= right)
    best = best_of(np.concatenate([px, vx[ok]]), np.concatenate([py, vy[ok]]), x, y, hue)
    return best if best[0] or not len(x) else best_of(np.clip(x[:1], left, right), y[:1], x, y, hue)


def trapezoids(x, y, hue, left: float = -math.inf, right: float = math.inf):
    """(cells: places, links across arcs and walls, crossing places) of the vertical decomposition of the unions' boundaries.

    A cell lies between two pieces and two walls; a wall ends at the first piece above and below its event, as
    neighbours that an event does not part go on as they are.  Only what an event changes is worked on.  A link
    (a, b, d) says that b is d deeper than a.  Cell 0 is outside.
    """
    import numpy as np

    disk, upper, met, slabs = slab_order(x, y, hue, left, right)
    sign, none = np.where(upper, -1, 1), len(disk)
    cells, links = [(math.nan, math.nan)], []
    codes = ids = over_before = None
    edge = -math.inf
    for a, b, over, h in slabs:
        bounds = np.concatenate([[none], over, [none]])
        now = bounds[:-1].astype(np.int64) * (none + 1) + bounds[1:]
        here = np.full(len(now), -1, dtype=np.int64)
        joined = codes is not None and a - edge <= TOL
        if joined:
            at = np.argsort(codes, kind="stable")
            k = np.minimum(np.searchsorted(codes[at], now), len(codes) - 1)
            same = codes[at[k]] == now
            here[same] = ids[at[k[same]]]
        here[[0, -1]] = 0  # below and above everything is outside
        fresh = np.flatnonzero(here < 0)
        walls = wall_before = None
        for r in fresh.tolist():
            here[r] = len(cells)
            cells.append(((a + b) / 2, float(h[over[r - 1]] + h[over[r]]) / 2))
        for r in fresh.tolist():
            links.append((int(here[r - 1]), int(here[r]), int(sign[over[r - 1]])))
            links.append((int(here[r]), int(here[r + 1]), int(sign[over[r]])))
            if joined and len(over_before):
                if walls is None:
                    walls = heights(a, x, y, disk[over], upper[over])
                    wall_before = heights(a, x, y, disk[over_before], upper[over_before])
                # the cells before the wall that share a stretch of it
                first = int(np.searchsorted(wall_before, walls[r - 1] + WIDEN))
                last = int(np.searchsorted(wall_before, walls[r] - WIDEN))
                links += [(int(ids[q]), int(here[r]), 0) for q in range(first, last + 1) if min(walls[r], wall_before[q] if q < len(wall_before) else math.inf) - max(walls[r - 1], wall_before[q - 1] if q else -math.inf) > WIDEN]
        codes, ids, over_before, edge = now, here, over, b
    return cells, links, met


def propagate(n: int, links) -> list[int | None]:
    """Depths by breadth-first search from the outer cell: equal across walls, one more or less across arcs."""
    near: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for a, b, d in links:
        near[a].append((b, d))
        near[b].append((a, -d))
    depth: list[int | None] = [None] * n
    if n:
        depth[0] = 0
    queue = deque([0] if n else [])
    while queue:
        c = queue.popleft()
        for o, d in near[c]:
            if depth[o] is None:
                depth[o] = depth[c] + d
                queue.append(o)
    return depth


def trapezoid_kernel(x, y, hue, floor: int = 0, centre=None, near: float = math.inf):
    """The deepest cell of the trapezoidal map, its depth found by walking the map from outside; clipped to a strip with a centre."""
    left, right = strip(centre, near)
    cells, links, met = trapezoids(x, y, hue, left, right)
    depth = propagate(len(cells), links)
    top = max(range(len(cells)), key=lambda c: depth[c] or 0)
    place = [cells[top]] if depth[top] else []
    return with_pinches([p[0] for p in place], [p[1] for p in place], met, x, y, hue, left, right)


KERNELS = {"sweep": sweep_kernel, "slab": slab_kernel, "trapezoid": trapezoid_kernel}
