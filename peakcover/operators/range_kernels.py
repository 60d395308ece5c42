"""Sweeps over index ranges: the place where closed ranges of two axes cover the most weight, or most colours.

Coordinates are ranks, so no rounding enters here.  A tree over the second axis is solved level by level: what the
best leaf below a node holds is a step function of the first axis, and the steps of all nodes of a level come from
one sort of their children's steps.  Cells lie side by side on both axes, so many are solved at once.
"""

from __future__ import annotations

import numpy as np


def _starts(first: np.ndarray) -> np.ndarray:
    return np.maximum.accumulate(np.where(first, np.arange(len(first)), 0))


def _edges(*keys: np.ndarray) -> np.ndarray:
    """Where a new combination of the sorted keys begins."""
    new = np.zeros(len(keys[0]), bool)
    new[:1] = True
    for k in keys:
        new[1:] |= k[1:] != k[:-1]
    return new


def deepest(t0, t1, l0, l1, w, leaves: int):
    """(depth, t, leaf): the first best place of the ranges t0..t1 x l0..l1 (both ends in), or None without any."""
    if not len(w):
        return None
    size = 1 << max(0, int(leaves - 1).bit_length())
    span = int(t1.max()) + 2
    lo, hi = l0 + size, l1 + size + 1
    node, at, val, arg = (np.zeros(0, np.int64),) * 2 + (np.zeros(0, w.dtype), np.zeros(0, np.int64))
    for level in range(size.bit_length()):
        left, right = (lo < hi) & (lo & 1 == 1), (lo < hi) & (hi & 1 == 1)
        mine = np.concatenate([np.flatnonzero(left), np.flatnonzero(right)])
        own = np.concatenate([lo[left], hi[right] - 1])
        lo, hi = (lo + 1) >> 1, hi >> 1
        up = 0 if level == 0 else 1
        kind = np.concatenate([node & 1, np.full(2 * len(mine), 2)])
        node = np.concatenate([node >> up, own, own])
        at = np.concatenate([at, t0[mine], t1[mine] + 1])
        val = np.concatenate([val, w[mine], -w[mine]])
        arg = np.concatenate([arg, np.zeros(2 * len(mine), np.int64)])
        if not len(node):
            continue
        order = np.argsort(node * span + at, kind="stable")
        node, at, val, arg, kind = node[order], at[order], val[order], arg[order], kind[order]
        start = _starts(_edges(node))
        held = np.cumsum(np.where(kind == 2, val, 0))
        held = held - (held[start] - np.where(kind[start] == 2, val[start], 0))
        if level:
            below = []
            for side in (0, 1):
                seen = np.maximum.accumulate(np.where(kind == side, np.arange(len(kind)), -1))
                known = seen >= start
                below.append((np.where(known, val[seen], 0), np.where(known, arg[seen], ((2 * node + side) << (level - 1)) - size)))
            (lv, la), (rv, ra) = below
            val, arg = held + np.maximum(lv, rv), np.where(rv > lv, ra, la)
        else:
            val, arg = held, node - size
        last = np.append(_edges(node, at)[1:], True)
        node, at, val, arg = node[last], at[last], val[last], arg[last]
    i = int(np.argmax(val))
    return val[i], int(at[i]), int(arg[i])


def reach(cell, value, own, side):
    """(from, to, first, last, places): the ranks of the places in a row's cell from which it is within reach.

    ``own`` marks the rows whose value is a place of their cell; first and last are the cell's ranks.  A row without
    a value (NaN) is within reach of every place of its cell.
    """
    places = np.unique(np.stack([cell[own].astype(np.float64), value[own]]), axis=1)
    pc, pv = places[0].astype(np.int64), places[1]
    known = ~np.isnan(value)
    first, last = np.searchsorted(pc, cell, "left"), np.searchsorted(pc, cell, "right") - 1
    ends = np.unique(np.concatenate([value[known], pv, pv + side]))
    rank = lambda v: np.searchsorted(ends, v)
    n = len(ends) + 1
    at = cell * n + rank(np.where(known, value, 0.0))
    begin = np.where(known, np.searchsorted(pc * n + rank(pv + side), at, "left"), first)
    end = np.where(known, np.searchsorted(pc * n + rank(pv), at, "right") - 1, last)
    return begin, end, first, last, pv


def _running(group, value, groups: int, backward: bool):
    """The running maximum inside each group of sorted rows; values are -1 or more."""
    wide = int(value.max()) + 2 if len(value) else 1
    if backward:
        return np.maximum.accumulate((value + (groups - group) * wide)[::-1])[::-1] - (groups - group) * wide
    return np.maximum.accumulate(value + group * wide) - group * wide


def disjoint(group, t0, t1, l0, l1, tf, tl, lf, ll):
    """The union of each group's ranges as disjoint ranges, at most two for each of its ends.

    ``tf, tl`` and ``lf, ll`` are the first and last ranks of the group's cell.  Cells are smaller than the ranges,
    so a range holds one end of its cell on either axis, and at every t a group covers a head and a tail of l.
    """
    left, lower = t0 == tf, l0 == lf
    if not ((left | (t1 == tl)) & (lower | (l1 == ll))).all():
        raise ValueError("coordinates are too large for sides of this size")
    wide = int(t1.max()) + 2 if len(t1) else 1
    ends = np.unique(np.concatenate([group * wide + t0, group * wide + t1 + 1]))
    g, t = ends // wide, ends % wide
    top = int(ll.max()) if len(ll) else 0
    begin, end = np.searchsorted(ends, group * wide + t0), np.searchsorted(ends, group * wide + t1 + 1)
    groups = int(group.max()) + 1 if len(group) else 1

    def held(rows, value):
        fore, back = np.full(len(ends), -1), np.full(len(ends), -1)
        np.maximum.at(fore, begin[rows & ~left], value[rows & ~left])
        np.maximum.at(back, end[rows & left] - 1, value[rows & left])
        return np.maximum(_running(g, fore, groups, False), _running(g, back, groups, True))

    head, tail = held(lower, l1), held(~lower, top - l0)
    inner = np.append(g[1:] == g[:-1], False)  # a group's last end closes it
    until = np.append(t[1:], 0) - 1
    row = np.searchsorted(group, g, "left")  # a row of the group, for its cell
    head_from, tail_to = lf[row], ll[row]
    whole = (head >= 0) & (tail >= 0) & (top - tail <= head + 1)
    a, b = inner & (head >= 0), inner & (tail >= 0) & ~whole
    upto = np.where(whole, tail_to, head)
    return np.concatenate([t[a], t[b]]), np.concatenate([until[a], until[b]]), np.concatenate([head_from[a], (top - tail)[b]]), np.concatenate([upto[a], tail_to[b]])


def solve_cells(cell, x, y, own_x, own_y, value, a: float, b: float, coloured: bool):
    """(depth, x0, y0) of the best lower left corner of an a x b rectangle in any of the cells, or None.

    ``value`` is a weight, or with ``coloured`` a colour's number.
    """
    t0, t1, tf, tl, xs = reach(cell, x, own_x, a)
    l0, l1, lf, ll, ys = reach(cell, y, own_y, b)
    met = (t0 <= t1) & (l0 <= l1)
    parts = [v[met] for v in (t0, t1, l0, l1)]
    if not met.any():
        return None
    if coloured:
        pair = np.unique(np.stack([cell[met], value[met]]), axis=1, return_inverse=True)[1].ravel()
        order = np.argsort(pair, kind="stable")
        parts = disjoint(pair[order], *(v[order] for v in parts), *(v[met][order] for v in (tf, tl, lf, ll)))
        weight = np.ones(len(parts[0]), np.int64)
    else:
        weight = value[met]
    depth, t, leaf = deepest(*parts, weight, len(ys))
    return depth, float(xs[t]), float(ys[leaf])


def _slabs(v: np.ndarray, w: np.ndarray, edges: np.ndarray, side: float):
    """(order, begin, end, held): the rows in order of v, and for each lower edge its run of them and its weight."""
    order = np.argsort(v, kind="stable")
    total = np.concatenate([[0], np.cumsum(w[order])])
    begin, end = np.searchsorted(v[order], edges, "left"), np.searchsorted(v[order], edges + side, "right")
    return order, begin, end, total[end] - total[begin]


def best_box(at: np.ndarray, own: np.ndarray, w: np.ndarray, sides: list[float], known=0):
    """The most weight in a box whose lower edges are coordinates of ``own`` rows of the cell, if above ``known``.

    All axes but two are fixed one lower edge after the other, the heaviest slab first; the last two are swept, unless
    an axis alone shows that ``known`` is not passed.
    """
    for i, side in enumerate(sides):
        edges = np.unique(at[own[:, i], i])
        if not len(edges) or _slabs(at[:, i], w, edges, side)[3].max() <= known:
            return known
    if len(sides) == 2:
        got = solve_cells(np.zeros(len(w), np.int64), at[:, 0], at[:, 1], own[:, 0], own[:, 1], w, sides[0], sides[1], False)
        return known if got is None else max(known, got[0])
    order, begin, end, held = _slabs(at[:, 0], w, np.unique(at[own[:, 0], 0]), sides[0])
    for i in np.argsort(-held, kind="stable"):
        if held[i] <= known:
            break
        rows = order[begin[i]:end[i]]
        known = best_box(at[rows, 1:], own[rows, 1:], w[rows], sides[1:], known)
    return known
