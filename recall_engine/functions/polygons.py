"""General simple polygons: the nine-cell matrix of interiors, boundaries and exteriors, simplification and projection.

The matrix is computed by splitting each ring's edges at the other ring and placing the midpoints of the pieces: inside,
on the border or outside. Coordinates on a lattice of moderate size are exact; otherwise a tolerance decides.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOLERANCE = 1e-9
RADIUS = 6_378_137.0
TOP_LATITUDE = 85.0511287798066


def clean(ring) -> np.ndarray:
    """Corners as an (m, 2) array without repeated neighbours or a closing point."""
    r = np.asarray([(p["x"], p["y"]) if not isinstance(p, (tuple, list, np.ndarray)) else (p[0], p[1]) for p in ring], float).reshape(-1, 2)
    if len(r):
        r = r[np.any(r != np.roll(r, 1, axis=0), axis=1)]
    return r


def locate(points: np.ndarray, ring: np.ndarray, tol: float = TOLERANCE) -> np.ndarray:
    """1 inside, 0 on the border, -1 outside."""
    a, b = ring, np.roll(ring, -1, axis=0)
    x, y = points[:, :1], points[:, 1:]
    cross = (b[:, 0] - a[:, 0]) * (y - a[:, 1]) - (b[:, 1] - a[:, 1]) * (x - a[:, 0])
    length = np.hypot(b[:, 0] - a[:, 0], b[:, 1] - a[:, 1])
    along = (x - a[:, 0]) * (b[:, 0] - a[:, 0]) + (y - a[:, 1]) * (b[:, 1] - a[:, 1])
    scale = tol * (1 + np.abs(ring).max())
    on = (np.abs(cross) <= scale * length) & (along >= -scale * length) & (along <= length**2 + scale * length)
    span = (a[:, 1] > y) != (b[:, 1] > y)
    with np.errstate(divide="ignore", invalid="ignore"):
        at = (b[:, 0] - a[:, 0]) * (y - a[:, 1]) / (b[:, 1] - a[:, 1]) + a[:, 0]
    inside = (span & (x < at)).sum(axis=1) % 2 == 1
    return np.where(on.any(axis=1), 0, np.where(inside, 1, -1))


def pieces(ring: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Midpoints of the ring's edges, cut wherever they meet the other ring."""
    out = []
    c, d = other, np.roll(other, -1, axis=0)
    for p, q in zip(ring, np.roll(ring, -1, axis=0), strict=True):
        r, s = q - p, d - c
        den = r[0] * s[:, 1] - r[1] * s[:, 0]
        w = c - p
        with np.errstate(divide="ignore", invalid="ignore"):
            t = (w[:, 0] * s[:, 1] - w[:, 1] * s[:, 0]) / den
            u = (w[:, 0] * r[1] - w[:, 1] * r[0]) / den
        hit = t[(den != 0) & (t > 0) & (t < 1) & (u >= -1e-12) & (u <= 1 + 1e-12)]
        line = np.abs(w[:, 0] * r[1] - w[:, 1] * r[0]) <= TOLERANCE * (1 + np.abs(other).max()) * math.hypot(*r)
        shadow = (w[line] @ r) / (r @ r)  # corners of the other ring on this edge
        cuts = np.unique(np.concatenate([[0.0, 1.0], hit, shadow[(shadow > 0) & (shadow < 1)]]))
        out.append(p + np.outer((cuts[:-1] + cuts[1:]) / 2, r))
    return np.concatenate(out)


def interior_point(ring: np.ndarray) -> np.ndarray:
    """Some point inside: the middle of the widest stretch of a horizontal line between two corner heights."""
    ys = np.unique(ring[:, 1])
    y = (ys[0] + ys[1]) / 2 if len(ys) > 1 else ys[0]
    a, b = ring, np.roll(ring, -1, axis=0)
    span = (a[:, 1] > y) != (b[:, 1] > y)
    xs = np.sort(a[span, 0] + (y - a[span, 1]) * (b[span, 0] - a[span, 0]) / (b[span, 1] - a[span, 1]))
    k = int(np.argmax(xs[1::2] - xs[::2]))
    return np.array([(xs[2 * k] + xs[2 * k + 1]) / 2, y])


def matrix(ring_a, ring_b) -> str | None:
    """The nine cells as dimensions: interior, boundary and exterior of a by those of b. None for fewer than three corners."""
    a, b = clean(ring_a), clean(ring_b)
    if len(a) < 3 or len(b) < 3:
        return None
    ab, ba = locate(pieces(a, b), b), locate(pieces(b, a), a)
    a_in_b, b_in_a = locate(interior_point(a)[None], b)[0], locate(interior_point(b)[None], a)[0]
    ii = bool((ab == 1).any() or (ba == 1).any() or a_in_b == 1 or b_in_a == 1)
    equal = bool((ab == 0).all() and (ba == 0).all())
    ii = ii or equal
    ib, bi = bool((ba == 1).any()), bool((ab == 1).any())
    ie = bool((ab == -1).any() or (ba == 1).any() or (not ii))
    ei = bool((ba == -1).any() or (ab == 1).any() or (not ii))
    corner = bool((locate(a, b) == 0).any() or (locate(b, a) == 0).any())
    crossing = bool(((ab == 1).any() and (ab == -1).any()) or ((ba == 1).any() and (ba == -1).any()))
    bb = "1" if (ab == 0).any() or (ba == 0).any() else "0" if corner or crossing else "F"
    cell = lambda on, dim: dim if on else "F"
    return "".join([cell(ii, "2"), cell(ib, "1"), cell(ie, "2"), cell(bi, "1"), bb, cell((ab == -1).any(), "1"), cell(ei, "2"), cell((ba == -1).any(), "1"), "2"])


MASKS = {
    "equals": ["T*F**FFF*"], "disjoint": ["FF*FF****"], "touches": ["FT*******", "F**T*****", "F***T****"], "contains": ["T*****FF*"], "within": ["T*F**F***"],
    "covers": ["T*****FF*", "*T****FF*", "***T**FF*", "****T*FF*"], "covered_by": ["T*F**F***", "*TF**F***", "**FT*F***", "**F*TF***"], "overlaps": ["T*T***T**"],
}


def matches(m: str | None, mask: str) -> bool:
    """T is any dimension, F empty, * anything, a digit itself."""
    return m is not None and all(k == "*" or (k == "T" and c != "F") or k == c for c, k in zip(m, mask, strict=True))


def holds(m: str | None, pred: str) -> bool:
    if pred == "intersects":
        return m is not None and not holds(m, "disjoint")
    return any(matches(m, k) for k in MASKS[pred])


def _place_all(x: np.ndarray, y: np.ndarray, ring: np.ndarray, tol: float = TOLERANCE) -> np.ndarray:
    """``locate`` for many rings at once: points (n, k) by rings (n, m, 2)."""
    x, y = x[:, :, None], y[:, :, None]
    a, b = ring[:, None], np.roll(ring, -1, axis=1)[:, None]
    dx, dy, wx, wy = b[..., 0] - a[..., 0], b[..., 1] - a[..., 1], x - a[..., 0], y - a[..., 1]
    length = np.hypot(dx, dy)
    along = wx * dx + wy * dy
    scale = (tol * (1 + np.abs(ring).max(axis=(1, 2))))[:, None, None]
    on = (np.abs(dx * wy - dy * wx) <= scale * length) & (along >= -scale * length) & (along <= length**2 + scale * length)
    span = (a[..., 1] > y) != (b[..., 1] > y)
    at = dx * wy / np.where(dy == 0, 1.0, dy) + a[..., 0]  # no span where dy is 0
    inside = (span & (x < at)).sum(axis=2) % 2 == 1
    return np.where(on.any(axis=2), 0, np.where(inside, 1, -1))


def _pieces_all(ring: np.ndarray, other: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``pieces`` for many rings at once: x and y (n, k) of the midpoints, and which of them are any."""
    p, c = ring[:, :, None], other[:, None]
    r, s, w = np.roll(ring, -1, axis=1)[:, :, None] - p, np.roll(other, -1, axis=1)[:, None] - c, c - p
    den = r[..., 0] * s[..., 1] - r[..., 1] * s[..., 0]
    cross = w[..., 0] * r[..., 1] - w[..., 1] * r[..., 0]
    some = np.where(den == 0, 1.0, den)
    t, u = (w[..., 0] * s[..., 1] - w[..., 1] * s[..., 0]) / some, cross / some
    hit = (den != 0) & (t > 0) & (t < 1) & (u >= -1e-12) & (u <= 1 + 1e-12)
    line = np.abs(cross) <= (TOLERANCE * (1 + np.abs(other).max(axis=(1, 2))))[:, None, None] * np.hypot(r[..., 0], r[..., 1])
    shadow = (w * r).sum(axis=-1) / (r * r).sum(axis=-1)
    on = line & (shadow > 0) & (shadow < 1)
    ends = np.zeros((*t.shape[:2], 1))
    cuts = np.sort(np.concatenate([ends, ends + 1, np.where(hit, t, 1.0), np.where(on, shadow, 1.0)], axis=2), axis=2)
    middle = (cuts[..., :-1] + cuts[..., 1:]) / 2
    n = len(ring)
    return tuple((p[..., k] + middle * r[..., k]).reshape(n, -1) for k in (0, 1)) + ((cuts[..., 1:] > cuts[..., :-1]).reshape(n, -1),)


def _interior_all(ring: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``interior_point`` of many rings at once."""
    low = ring[:, :, 1].min(axis=1)
    above = np.where(ring[:, :, 1] > low[:, None], ring[:, :, 1], np.inf).min(axis=1)
    y = np.where(np.isinf(above), low, (low + above) / 2)
    a, b = ring, np.roll(ring, -1, axis=1)
    span = (a[..., 1] > y[:, None]) != (b[..., 1] > y[:, None])
    dy = b[..., 1] - a[..., 1]
    xs = np.sort(np.where(span, a[..., 0] + (y[:, None] - a[..., 1]) * (b[..., 0] - a[..., 0]) / np.where(dy == 0, 1.0, dy), np.inf), axis=1)
    m = xs.shape[1] // 2 * 2
    lo, hi = xs[:, :m:2], xs[:, 1:m:2]
    k = np.argmax(np.where(np.isinf(hi), -np.inf, hi - np.where(np.isinf(lo), 0.0, lo)), axis=1)
    row = np.arange(len(ring))
    return (lo[row, k] + hi[row, k]) / 2, y


def matrices(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """``matrix`` of many pairs at once, for clean rings (n, m, 2) and (n, k, 2) of three corners and more."""
    (ax, ay, a_any), (bx, by, b_any) = _pieces_all(a, b), _pieces_all(b, a)
    ab, ba = _place_all(ax, ay, b), _place_all(bx, by, a)
    is_ab, is_ba = ({k: ((at == k) & some).any(axis=1) for k in (-1, 0, 1)} for at, some in ((ab, a_any), (ba, b_any)))
    inner = []
    for one, two in ((a, b), (b, a)):
        x, y = _interior_all(one)
        inner.append(_place_all(x[:, None], y[:, None], two)[:, 0] == 1)
    equal = ~(is_ab[1] | is_ab[-1] | is_ba[1] | is_ba[-1])
    ii = is_ab[1] | is_ba[1] | inner[0] | inner[1] | equal
    corner = (_place_all(a[..., 0], a[..., 1], b) == 0).any(axis=1) | (_place_all(b[..., 0], b[..., 1], a) == 0).any(axis=1)
    crossing = (is_ab[1] & is_ab[-1]) | (is_ba[1] & is_ba[-1])
    bb = np.where(is_ab[0] | is_ba[0], "1", np.where(corner | crossing, "0", "F"))
    cells = [np.where(on, dim, "F") for on, dim in ((ii, "2"), (is_ba[1], "1"), (is_ab[-1] | is_ba[1] | ~ii, "2"), (is_ab[1], "1"))]
    cells += [bb, *[np.where(on, dim, "F") for on, dim in ((is_ab[-1], "1"), (is_ba[-1] | is_ab[1] | ~ii, "2"), (is_ba[-1], "1"))], np.full(len(a), "2")]
    return np.array(["".join(c) for c in zip(*cells, strict=True)], object)


def _clean_all(rings: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Corners of all rings, as ``clean`` leaves them, and each ring's first one (n + 1); a null ring has none."""
    size = pc.fill_null(pc.list_value_length(rings), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = rings.flatten()
    xy = np.stack([pc.struct_field(flat, k).to_numpy(zero_copy_only=False) for k in ("x", "y")], axis=1).astype(float)
    start = np.concatenate([[0], np.cumsum(size)])
    before = np.arange(len(xy)) - 1
    some = size > 0
    before[start[:-1][some]] = start[1:][some] - 1
    keep = np.any(xy != xy[before], axis=1) if len(xy) else np.zeros(0, bool)
    return xy[keep], np.concatenate([[0], np.cumsum(keep)])[start]


#: Pairs of rings that are placed at a time.
AT_ONCE = 512


def related(pairs: DataFrame, a: str = "s_ring", b: str = "t_ring") -> DataFrame:
    """``pairs`` with their matrix; rings reach Python in Arrow batches, and those of equal numbers of corners are placed together."""
    rest = [c for c in pairs.columns if c not in (a, b)]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in pairs.schema if f.name in rest] + ["matrix string"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            (p, p_at), (q, q_at) = _clean_all(batch.column(len(rest))), _clean_all(batch.column(len(rest) + 1))
            m, k = np.diff(p_at), np.diff(q_at)
            out = np.full(batch.num_rows, None, object)
            for sizes in {(i, j) for i, j in zip(m.tolist(), k.tolist(), strict=True) if i >= 3 and j >= 3}:
                rows = np.flatnonzero((m == sizes[0]) & (k == sizes[1]))
                step = max(1, AT_ONCE * 64 // (sizes[0] * sizes[1]))
                for lo in range(0, len(rows), step):
                    at = rows[lo : lo + step]
                    out[at] = matrices(p[p_at[at][:, None] + np.arange(sizes[0])], q[q_at[at][:, None] + np.arange(sizes[1])])
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(rest)], pa.array(out, pa.string())], names=[*rest, "matrix"])

    return pairs.select(*rest, a, b).mapInArrow(run, schema)


def simplify(ring: np.ndarray, eps: float = 0.1) -> np.ndarray:
    """Polyline reduction: from two far corners on, the farthest corner of a stretch stays if it is more than ``eps`` off its chord. Without recursion."""
    ring = clean(ring)
    if len(ring) <= 3:
        return ring
    far = int(np.argmax(((ring - ring[0]) ** 2).sum(axis=1)))
    closed = np.vstack([ring, ring[:1]])
    keep = np.zeros(len(closed), bool)
    keep[[0, far, len(ring)]] = True
    todo = [(0, far), (far, len(ring))]
    while todo:
        i, j = todo.pop()
        if j - i < 2:
            continue
        p, q = closed[i], closed[j]
        d = q - p
        inner = closed[i + 1 : j] - p
        length = math.hypot(*d)
        off = np.abs(d[0] * inner[:, 1] - d[1] * inner[:, 0]) / length if length else np.hypot(inner[:, 0], inner[:, 1])
        k = int(np.argmax(off))
        if off[k] > eps:
            keep[i + 1 + k] = True
            todo += [(i, i + 1 + k), (i + 1 + k, j)]
    out = closed[:-1][keep[:-1]]
    return out if len(out) >= 3 else ring


def simplified(rows: DataFrame, ring: str = "ring", eps: float = 0.1) -> DataFrame:
    """``rows`` with every ring reduced."""
    names = rows.columns

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            f[ring] = [[{"x": float(x), "y": float(y)} for x, y in simplify(r, eps)] for r in f[ring]]
            yield f[names]

    return rows.mapInPandas(run, rows.schema)


def to_metres(lon: Column, lat: Column) -> tuple[Column, Column]:
    """Spherical Mercator; latitudes are clamped where its square ends."""
    phi = F.radians(F.greatest(F.lit(-TOP_LATITUDE), F.least(F.lit(TOP_LATITUDE), lat)))
    return F.radians(lon) * RADIUS, F.ln(F.tan(F.lit(math.pi / 4) + phi / 2)) * RADIUS
