"""Numpy kernels on movements: alignment, refinement, synchronised average distance, cylinders.

A movement is three arrays of equal length: s (ascending, 0 to 1 once aligned), x and y. Many movements are one flat
block of vertices with offsets; the one-to-many kernels below make one pass over such a block.
"""

from __future__ import annotations

import numpy as np

STILL = 1e-9  # relative displacement under which two positions move in parallel


def align(t, x, y, mode: str = "time"):
    """Map a movement to the interval [0, 1]; one instant becomes a stationary movement.

    ``mode='spatial'`` drops the times: s grows with the length of the path, so the speed is constant.
    """
    t, x, y = (np.asarray(a, np.float64) for a in (t, x, y))
    if mode == "spatial":
        t = np.concatenate([[0.0], np.cumsum(np.hypot(np.diff(x), np.diff(y)))])
    elif mode != "time":
        raise ValueError(f"no alignment mode {mode!r}")
    if len(t) == 1 or t[-1] == t[0]:
        return np.array([0.0, 1.0]), np.array([x[0], x[-1]]) if mode == "spatial" else np.array([x[0], x[0]]), np.array([y[0], y[-1]]) if mode == "spatial" else np.array([y[0], y[0]])
    s = (t - t[0]) / (t[-1] - t[0])
    s[-1] = 1.0
    return s, x, y


def close_gaps(units):
    """Units (t0, t1, x0, y0, x1, y1) with a unit put into each gap in time; a jump without a gap stays."""
    out = []
    for u in units:
        if out and u[0] > out[-1][1]:
            p = out[-1]
            out.append((p[1], u[0], p[4], p[5], u[2], u[3]))
        out.append(tuple(u))
    return out


def units_to_vertices(units):
    """Vertices (t, x, y) of gap-free units whose ends meet."""
    units = close_gaps(units)
    rows = [(u[0], u[2], u[3]) for u in units] + [(units[-1][1], units[-1][4], units[-1][5])]
    return tuple(np.array(c, np.float64) for c in zip(*rows, strict=True))


def refine(s, t):
    """Common breakpoints of two aligned movements."""
    return np.union1d(s, t)


def segment_mean(px, py, qx, qy):
    """Mean length of a displacement that goes linearly from p to q: the integral of a square root of a quadratic.

    With g = q - p and L = |g|: parallel movements give the mean of both lengths; otherwise the displacement passes
    the origin at distance h, and the antiderivative of sqrt(x^2 + h^2) is taken between a and a + L.
    """
    px, py, qx, qy = (np.asarray(a, np.float64) for a in (px, py, qx, qy))
    gx, gy = qx - px, qy - py
    length = np.sqrt(gx * gx + gy * gy)
    ends = np.sqrt(px * px + py * py) + np.sqrt(qx * qx + qy * qy)
    still = length <= STILL * ends
    safe = np.where(still, 1.0, length)
    a = (px * gx + py * gy) / safe
    b = a + length
    h = np.abs(px * gy - py * gx) / safe
    near = h > 0
    hs = np.where(near, h, 1.0)

    def primitive(v):
        return 0.5 * (v * np.sqrt(v * v + h * h) + np.where(near, h * h * np.arcsinh(v / hs), 0.0))

    return np.where(still, ends / 2, (primitive(b) - primitive(a)) / safe)


def moving_distance(u, v):
    """Time-dependent distance: (s0, s1, a, b, c) with distance sqrt(a s^2 + b s + c) on each common interval."""
    s = refine(u[0], v[0])
    dx = np.interp(s, v[0], v[1]) - np.interp(s, u[0], u[1])
    dy = np.interp(s, v[0], v[2]) - np.interp(s, u[0], u[2])
    s0, s1 = s[:-1], s[1:]
    kx, ky = np.diff(dx) / (s1 - s0), np.diff(dy) / (s1 - s0)
    ox, oy = dx[:-1] - kx * s0, dy[:-1] - ky * s0
    return s0, s1, kx * kx + ky * ky, 2 * (kx * ox + ky * oy), ox * ox + oy * oy


def value_at(moving, s: float) -> float:
    """Distance at time s from the quadratic of its interval."""
    s0, s1, a, b, c = moving
    i = min(int(np.searchsorted(s1, s)), len(s0) - 1)
    return float(np.sqrt(max(a[i] * s * s + b[i] * s + c[i], 0.0)))


def sad(u, v) -> float:
    """Synchronised average distance of two aligned movements."""
    if not (u[0][0] == v[0][0] == 0.0 and u[0][-1] == v[0][-1] == 1.0):
        raise ValueError("align both movements first")
    s = refine(u[0], v[0])
    dx = np.interp(s, v[0], v[1]) - np.interp(s, u[0], u[1])
    dy = np.interp(s, v[0], v[2]) - np.interp(s, u[0], u[2])
    return float((segment_mean(dx[:-1], dy[:-1], dx[1:], dy[1:]) * np.diff(s)).sum())


def sad_same_interval(u, v) -> float | None:
    """The same average on the movements' own interval, if it is one and the same; else None."""
    if u[0][0] != v[0][0] or u[0][-1] != v[0][-1]:
        return None
    return sad(align(*u), align(*v))


def flatten(movements):
    """One block (offsets, s, x, y) of a list of movements."""
    offsets = np.concatenate([[0], np.cumsum([len(m[0]) for m in movements])]).astype(np.int64)
    if not movements:
        return offsets, np.zeros(0), np.zeros(0), np.zeros(0)
    return offsets, *(np.concatenate([m[k] for m in movements]).astype(np.float64) for k in range(3))


def pick(block, index):
    """The sub-block of the movements at ``index``, in that order."""
    offsets, s, x, y = block
    starts, lengths = offsets[index], offsets[np.asarray(index) + 1] - offsets[index]
    out = np.concatenate([[0], np.cumsum(lengths)])
    at = np.repeat(starts - out[:-1], lengths) + np.arange(out[-1])
    return out, s[at], x[at], y[at]


def sad_many(q, block):
    """Synchronised average distance of q to each movement of a block, in one pass over merged breakpoints.

    The breakpoints of q and of each movement are merged without a sort: a vertex stands behind those before it in its
    own movement and those of the other that come earlier, both of which are counted; at equal times q's come last.
    """
    offsets, s, x, y = block
    n, m = len(offsets) - 1, len(q[0])
    if n == 0:
        return np.zeros(0)
    lengths, every = np.diff(offsets), np.arange(n)
    owner = np.repeat(every, lengths)
    low = np.searchsorted(q[0], s, "left")
    upto = np.bincount(owner * (m + 1) + low, minlength=n * (m + 1)).reshape(n, m + 1).cumsum(axis=1)[:, :m]
    left = offsets[:-1, None] + upto - 1  # the last vertex not after each of q's
    right = np.minimum(left + 1, offsets[1:, None] - 1)
    from_, span = s[left], s[right] - s[left]
    w = np.where(span > 0, (q[0] - from_) / np.where(span > 0, span, 1.0), 0.0)
    mine = np.arange(len(s)) + owner * m + low
    other = left + 1 + every[:, None] * m + np.arange(m)
    time, dx, dy = (np.empty(len(s) + n * m) for _ in range(3))
    time[mine], time[other] = s, np.broadcast_to(q[0], (n, m))
    dx[mine], dx[other] = x - np.interp(s, q[0], q[1]), x[left] + w * (x[right] - x[left]) - q[1]
    dy[mine], dy[other] = y - np.interp(s, q[0], q[2]), y[left] + w * (y[right] - y[left]) - q[2]
    step = np.diff(time)
    step[(offsets[1:-1] + every[1:] * m) - 1] = 0.0  # from one movement to the next
    go = np.flatnonzero(step > 0)
    means = segment_mean(dx[go], dy[go], dx[go + 1], dy[go + 1]) * step[go]
    return np.bincount(np.repeat(every, lengths + m)[go], weights=means, minlength=n)


def hausdorff_many(q, block):
    """Hausdorff distance between the vertices of q and of each movement of a block."""
    offsets, _, x, y = block
    n = len(offsets) - 1
    out = np.zeros(n)
    step = max(1, int(4_000_000 // max(1, len(q[0]) * max(1, int(np.diff(offsets).max(initial=1))))))
    for first in range(0, n, step):
        end = min(n, first + step)
        a, b = offsets[first], offsets[end]
        d = np.hypot(x[None, a:b] - q[1][:, None], y[None, a:b] - q[2][:, None])
        cuts = offsets[first:end] - a
        out[first:end] = np.maximum(np.maximum.reduceat(d.min(axis=0), cuts), np.minimum.reduceat(d, cuts, axis=1).max(axis=0))
    return out


def frechet(u, v) -> float:
    """Discrete Frechet distance between the vertices of two movements."""
    d = np.hypot(u[1][:, None] - v[1][None, :], u[2][:, None] - v[2][None, :])
    row = np.maximum.accumulate(d[0])
    for i in range(1, len(d)):
        reach = np.minimum(row, np.concatenate([[np.inf], row[:-1]]))
        new = np.empty_like(row)
        best = np.inf
        for j in range(len(row)):
            best = max(d[i, j], min(best, reach[j]))
            new[j] = best
        row = new
    return float(row[-1])


def hull(m):
    """One oblique cylinder around a movement: end points of its axis and its radius (deviation at equal times)."""
    s, x, y = m
    ax, ay = x[0] + s * (x[-1] - x[0]), y[0] + s * (y[-1] - y[0])
    return float(x[0]), float(y[0]), float(x[-1]), float(y[-1]), float(np.hypot(x - ax, y - ay).max())


def hull_bounds(a, b):
    """Lower and upper bound of the distance of two movements from their hulls."""
    d = float(segment_mean(b[0] - a[0], b[1] - a[1], b[2] - a[2], b[3] - a[3]))
    return max(0.0, d - a[4] - b[4]), d + a[4] + b[4]


def simplify(m, radius: float):
    """Subsequence of the vertices whose connection stays within ``radius`` of the movement at every time."""
    s, x, y = m
    keep = np.zeros(len(s), bool)
    keep[[0, -1]] = True
    todo = [(0, len(s) - 1)]
    while todo:
        a, b = todo.pop()
        if b - a < 2:
            continue
        inner = slice(a + 1, b)
        span = s[b] - s[a]
        w = (s[inner] - s[a]) / span if span > 0 else np.zeros(b - a - 1)
        off = np.hypot(x[inner] - x[a] - w * (x[b] - x[a]), y[inner] - y[a] - w * (y[b] - y[a]))
        far = int(off.argmax())
        if off[far] > radius:
            keep[a + 1 + far] = True
            todo += [(a, a + 1 + far), (a + 1 + far, b)]
    return s[keep], x[keep], y[keep]


def tube(m, radius: float, repair: bool = True):
    """(tube, mean deviation, repaired): the simplified movement; redone at half the radius until the mean deviation
    is below half of the radius asked for, if ``repair``."""
    t, used, fixed = simplify(m, radius), radius, False
    err = sad(m, t)
    while repair and err >= radius / 2 and err > 0:
        used, fixed = used / 2, True
        t = simplify(m, used)
        err = sad(m, t)
    return t, err, fixed
