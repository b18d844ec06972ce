"""Array kernels for Arrow stages: draws, inside tests, first hits, intersection areas."""

from __future__ import annotations

import functools
import hashlib
import math

import numpy as np

SLOTS_PER_BAND = 16  # slot = band * 16 + place, so a longer signature extends a shorter one in each band


def draw(base: int, slot: int, axis: str, attempt: int) -> int:
    """A keyed uniform number in [0, 2**32)."""
    return int(hashlib.md5(f"{base}:{slot}:{axis}:{attempt}".encode()).hexdigest()[:8], 16)


_TURNS = (7, 12, 17, 22) * 4 + (5, 9, 14, 20) * 4 + (4, 11, 16, 23) * 4 + (6, 10, 15, 21) * 4
_SINES = tuple(int(abs(math.sin(i + 1)) * 2**32) for i in range(64))
_WORDS = (*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *(7 * i % 16 for i in range(16)))


def _heads(words: list, n: int) -> np.ndarray:
    """The first word of the MD5 of ``n`` messages of one block each; a word that all have is a number."""
    a, b, c, d = (np.full(n, v, np.uint32) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i, (turn, sine, w) in enumerate(zip(_TURNS, _SINES, _WORDS, strict=True)):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.bitwise_not(d, out=f)
            f |= b
            f ^= c
        a += f
        if isinstance(words[w], int):
            a += np.uint32((sine + words[w]) & 0xFFFFFFFF)
        else:
            a += words[w]
            a += np.uint32(sine)
        np.right_shift(a, np.uint32(32 - turn), out=t)
        np.left_shift(a, np.uint32(turn), out=a)
        a |= t
        a += b
        a, b, c, d = d, a, b, c
    a += np.uint32(0x67452301)
    return a.byteswap()


#: The last four digits of a number as the bytes of a word.
_DIGITS = sum((np.arange(10000, dtype=np.uint32) // 10 ** (3 - i) % 10 + 48).astype(np.uint32) << np.uint32(8 * i) for i in range(4))


def draws(base: int, slot: int, axis: str, first: int, last: int, only: np.ndarray | None = None) -> np.ndarray:
    """``draw`` of attempts ``first..last``; with a mask ``only`` of those that it marks.

    From ten thousand on all of one ten thousand at once: their messages differ in four bytes.
    """
    head = f"{base}:{slot}:{axis}:".encode()
    out, at = [np.zeros(0, np.uint32)], first
    while at <= last:
        to = min(last, at // 10000 * 10000 + 9999)
        tail = np.arange(at % 10000, to % 10000 + 1) if only is None else at % 10000 + np.flatnonzero(only[at - first : to + 1 - first])
        start = head + b"%d" % (at // 10000)
        if at < 10000 or len(tail) < 100 or len(start) > 51:  # too few, or longer than a block
            out.append(np.frombuffer(b"".join(hashlib.md5(head + b"%d" % (at // 10000 * 10000 + n)).digest()[:4] for n in tail.tolist()), ">u4"))
        else:
            size = len(start) + 4
            words = np.frombuffer(start + bytes(4) + b"\x80" + bytes(55 - size) + (8 * size).to_bytes(8, "little"), "<u4").tolist()
            digits, (w, off) = _DIGITS[tail], divmod(len(start), 4)
            if off:
                words[w + 1] = words[w + 1] | digits >> np.uint32(32 - 8 * off)
            words[w] = words[w] | digits << np.uint32(8 * off)
            out.append(_heads(words, len(digits)))
        at = to + 1
    return np.concatenate(out).astype(np.int64)


#: Points of attempts up to here are kept for the next shapes; later ones, which few shapes ask for, are drawn again.
KEPT = 1 << 16
#: How many of the later ones are drawn at a time.
LATER = 1 << 14


def points(frame: tuple[int, int, int, int], slots: tuple[int, ...], first: int, last: int, base: int = 42, within: tuple[int, int] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Odd-lattice sample points of attempts ``first..last`` (slots x attempts), x and y.

    Where x isn't ``within`` two bounds, y may be the frame's least, which lies in no shape.
    """
    return _kept(frame, slots, first, last, base) if last <= KEPT else _drawn(frame, slots, first, last, base, within)


def _drawn(frame: tuple[int, int, int, int], slots: tuple[int, ...], first: int, last: int, base: int, within: tuple[int, int] | None = None) -> tuple[np.ndarray, np.ndarray]:
    def placed(u: np.ndarray, low: int, high: int) -> np.ndarray:
        return low + 2 * ((u * ((high - low) // 2)) >> 32) + 1

    px = placed(np.stack([draws(base, s, "x", first, last) for s in slots]), *frame[:2])
    if within is None:
        return px, placed(np.stack([draws(base, s, "y", first, last) for s in slots]), *frame[2:])
    use, py = (px > within[0]) & (px < within[1]), np.full(px.shape, frame[2], np.int64)
    for row, some, s in zip(py, use, slots, strict=True):
        row[some] = placed(draws(base, s, "y", first, last, some), *frame[2:])
    return px, py


_kept = functools.lru_cache(maxsize=1024)(_drawn)


def inside(x: np.ndarray, y: np.ndarray, px: np.ndarray, py: np.ndarray) -> np.ndarray:
    """Whether each point lies in the ring, by crossing parity in integers."""
    x2, y2 = np.roll(x, -1), np.roll(y, -1)
    up, up2 = y[:, None] > py, y2[:, None] > py
    side = (x2 - x)[:, None] * (py - y[:, None]) - (y2 - y)[:, None] * (px - x[:, None])
    return ((up != up2) & (np.where((y2 > y)[:, None], side, -side) > 0)).sum(0) % 2 == 1


def centred_rings(x: np.ndarray, y: np.ndarray, size: np.ndarray) -> tuple:
    """Rings (flat, ``size`` vertices each) without a closing vertex, invalid ones dropped, centred on their area's centre.

    Returns which rings stayed, their coordinates and sizes, centre, doubled area
    and box (four arrays).
    """
    start = np.cumsum(size) - size
    # A closing vertex that repeats the first is no vertex.
    last = np.maximum(start + size - 1, 0)
    closed = (size > 1) & (x[np.minimum(last, len(x) - 1)] == x[np.minimum(start, len(x) - 1)]) & (y[np.minimum(last, len(y) - 1)] == y[np.minimum(start, len(y) - 1)]) if len(x) else np.zeros(len(size), bool)
    keep = np.ones(len(x), bool)
    keep[last[closed]] = False
    x, y, size = x[keep], y[keep], size - closed
    start = np.cumsum(size) - size
    own = np.repeat(np.arange(len(size)), size)
    order = np.lexsort((y, x, own))
    new = np.ones(len(x), bool)
    new[1:] = (own[order][1:] != own[order][:-1]) | (x[order][1:] != x[order][:-1]) | (y[order][1:] != y[order][:-1])
    distinct = np.bincount(own[order][new], minlength=len(size))
    full = np.flatnonzero(size > 0)
    low_x, low_y = np.zeros(len(size), np.int64), np.zeros(len(size), np.int64)
    if len(full):
        low_x[full], low_y[full] = np.minimum.reduceat(x, start[full]), np.minimum.reduceat(y, start[full])
    rx, ry = x - low_x[own], y - low_y[own]
    nxt = np.arange(len(x)) + 1
    nxt[(start + size - 1)[full]] = start[full]
    cross = rx * ry[nxt] - rx[nxt] * ry
    area2, mx, my = np.zeros((3, len(size)), np.int64)
    if len(full):
        area2[full] = np.add.reduceat(cross, start[full])
        mx[full] = np.abs(np.add.reduceat(cross * (rx + rx[nxt]), start[full]))
        my[full] = np.abs(np.add.reduceat(cross * (ry + ry[nxt]), start[full]))
    ok = (distinct >= 3) & (area2 != 0)
    area2 = np.abs(area2)
    gx, gy = (2 * (m // np.maximum(1, 6 * area2)) for m in (mx, my))
    stay = ok[own]
    ox, oy, n = (rx - gx[own])[stay], (ry - gy[own])[stay], size[ok]
    at = np.cumsum(n) - n
    box = [f.reduceat(v, at) if len(n) else np.zeros(0, np.int64) for v in (ox, oy) for f in (np.minimum, np.maximum)]
    return ok, ox, oy, n, (low_x + gx)[ok], (low_y + gy)[ok], area2[ok], box


def half_up(v: np.ndarray) -> np.ndarray:
    """Rounded half away from zero, as SQL rounds."""
    return (np.sign(v) * np.floor(np.abs(v) + 0.5)).astype(np.int64)


def radial(radii: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Even-lattice vertices of rows of radii at even angles."""
    d = radii.shape[1]
    turn = [2 * math.pi * t / d for t in range(d)]
    cos, sin = np.array([math.cos(a) for a in turn]), np.array([math.sin(a) for a in turn])
    return 2 * half_up(radii * cos / 2), 2 * half_up(radii * sin / 2)


CHUNKS, EARLY = (16, 64, 256, 1024, 4096), 80


def first_hits(x: np.ndarray, y: np.ndarray, frame: tuple[int, int, int, int], slots: tuple[int, ...], cap: int | None = None, base: int = 42, precheck: bool = True, seen: list[int] | None = None) -> np.ndarray:
    """Ordinal of the first point inside the ring for each slot; with a ``cap``, 0 if none up to it.

    Attempts are tried in growing chunks and a slot stops at its first hit; without
    a cap a ring of positive area is hit in the end, whatever its share of the frame.
    ``seen`` (a list of two) gains the attempts made and the inside tests done.
    """
    out = np.zeros(len(slots), np.int64)
    open_ = np.arange(len(slots))
    done = 0
    box = (x.min(), x.max(), y.min(), y.max())
    step = iter(CHUNKS)
    while len(open_) and (cap is None or done < cap):
        until = done + next(step, CHUNKS[-1])
        until = until if cap is None else min(cap, until)
        if done < EARLY:
            px, py = (v[open_] for v in points(frame, slots, done + 1, until, base))
        else:  # few slots come this far: theirs alone are drawn
            px, py = (np.concatenate(v) for v in zip(*(points(frame, (slots[i],), done + 1, until, base) for i in open_), strict=True))
        ok = (px > box[0]) & (px < box[1]) & (py > box[2]) & (py < box[3]) if precheck else np.ones(px.shape, bool)
        r, c = np.nonzero(ok)
        hit = np.zeros(px.shape, bool)
        if len(r):
            hit[r, c] = inside(x, y, px[r, c], py[r, c])
        any_ = hit.any(1)
        at = hit.argmax(1)
        if seen is not None:
            stop = np.where(any_, at + 1, until - done)
            seen[0] += int(stop.sum())
            seen[1] += int((ok & (np.arange(px.shape[1])[None] < stop[:, None])).sum())
        out[open_[any_]] = done + at[any_] + 1
        open_ = open_[~any_]
        done = until
    return out


STEPS, MOST_TESTS = (4, 12, 48, 192, 768, 3072), 1_000_000


def spans(at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Indices of all spans, one after another."""
    ends = np.cumsum(size)
    return np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - size, size) + np.repeat(at, size)


def first_hits_of(x: np.ndarray, y: np.ndarray, size: np.ndarray, frame: tuple[int, int, int, int], slots: tuple[int, ...], cap: int | None = None, base: int = 42, precheck: bool = True) -> np.ndarray:
    """``first_hits`` of many rings (flat, ``size`` vertices each) at once: rings x slots.

    Every open (ring, slot) is tried on the next few attempts; points that pass the
    box check meet the ring's edges in flat arrays of ``MOST_TESTS`` rows or a ring more.
    """
    start = np.cumsum(size) - size
    nxt = np.arange(len(x)) + 1
    nxt[start + size - 1] = start
    x2, y2 = x[nxt], y[nxt]
    dx, dy = x2 - x, y2 - y
    low_x, high_x, low_y, high_y = (f.reduceat(v, start) for v in (x, y) for f in (np.minimum, np.maximum))
    out = np.zeros(len(size) * len(slots), np.int64)
    ring, slot = np.repeat(np.arange(len(size)), len(slots)), np.tile(np.arange(len(slots)), len(size))
    done, step = 0, iter(STEPS)
    while len(ring) and (cap is None or done < cap):
        until = done + next(step, STEPS[-1] if done + STEPS[-1] <= KEPT else LATER)
        until = until if cap is None else min(cap, until)
        some = np.unique(slot)
        within = (low_x[ring].min(), high_x[ring].max()) if precheck else None
        px, py = (np.concatenate(v) for v in zip(*(points(frame, (slots[i],), done + 1, until, base, within) for i in some), strict=True))
        row = np.searchsorted(some, slot)
        first = np.zeros(len(ring), np.int64)
        for part in np.array_split(np.arange(len(ring)), max(1, len(ring) * (until - done) // MOST_TESTS)):
            r = ring[part]
            u, v = px[row[part]], py[row[part]]
            ok = (u > low_x[r, None]) & (u < high_x[r, None]) & (v > low_y[r, None]) & (v < high_y[r, None]) if precheck else np.ones(u.shape, bool)
            who, turn = np.nonzero(ok)
            hit = np.zeros(len(who), bool)
            for some_rows in blocks_of(size[r[who]]):
                w = who[some_rows]
                n = size[r[w]]
                e = spans(start[r[w]], n)
                a, b = np.repeat(u[w, turn[some_rows]], n), np.repeat(v[w, turn[some_rows]], n)
                side = dx[e] * (b - y[e]) - dy[e] * (a - x[e])
                cross = ((y[e] > b) != (y2[e] > b)) & (np.where(dy[e] > 0, side, -side) > 0)
                hit[some_rows] = np.add.reduceat(cross.astype(np.int64), np.cumsum(n) - n) % 2 == 1
            # Rows come in order of attempts, so the first hit of each stands first.
            at, where = np.unique(who[hit], return_index=True)
            first[part[at]] = done + turn[hit][where] + 1
        got = first > 0
        out[ring[got] * len(slots) + slot[got]] = first[got]
        ring, slot, done = ring[~got], slot[~got], until
    return out.reshape(len(size), len(slots))


def blocks_of(size: np.ndarray) -> list[slice]:
    """Slices of rows whose sizes add up to ``MOST_TESTS`` or a row more."""
    ends = np.cumsum(size)
    out, at = [], 0
    while at < len(size):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + MOST_TESTS, side="right")))
        out.append(slice(at, to))
        at = to
    return out


class Rings:
    """Edges of many rings, flat: sorted spans, lines and signs."""

    def __init__(self, xs: np.ndarray, ys: np.ndarray, starts: np.ndarray):
        size = np.diff(starts)
        self.n = len(size)
        own = np.repeat(np.arange(self.n), size)
        nxt = np.arange(len(xs)) + 1
        full = size > 0
        nxt[starts[1:][full] - 1] = starts[:-1][full]
        x1, y1, x2, y2 = xs.astype(float), ys.astype(float), xs[nxt].astype(float), ys[nxt].astype(float)
        cross = x1 * y2 - x2 * y1
        area2 = np.bincount(own, cross, self.n)
        self.area = np.abs(area2) / 2
        flat = x1 != x2
        swap = x1 > x2
        self.a, self.b = np.minimum(x1, x2)[flat], np.maximum(x1, x2)[flat]
        self.ya, self.yb = np.where(swap, y2, y1)[flat], np.where(swap, y1, y2)[flat]
        # An edge that runs left bounds a counter-clockwise ring from above.
        self.sign = (np.where(swap, 1.0, -1.0) * np.sign(area2)[own])[flat]
        self.own = own[flat]
        self.slope = (self.yb - self.ya) / (self.b - self.a)
        self.base = self.ya - self.a * self.slope
        self.box = np.stack([np.minimum.reduceat(xs, starts[:-1]), np.maximum.reduceat(xs, starts[:-1]), np.minimum.reduceat(ys, starts[:-1]), np.maximum.reduceat(ys, starts[:-1])], 1).astype(float) if self.n else np.zeros((0, 4))

    @functools.cached_property
    def ends(self) -> np.ndarray:
        """Where each ring's edges begin, and where the last one's end."""
        return np.searchsorted(self.own, np.arange(self.n + 1))

    def edges(self, k: int) -> slice:
        """Where ring ``k`` has its edges."""
        return slice(int(self.ends[k]), int(self.ends[k + 1]))

    def pick(self, at: np.ndarray) -> Rings:
        """The rings at these places, in their order."""
        out = object.__new__(Rings)
        start, end = self.ends[at], self.ends[at + 1]
        keep = spans(start, end - start)
        out.n, out.area, out.box = len(at), self.area[at], self.box[at]
        for f in ("a", "b", "ya", "yb", "sign", "slope", "base"):
            setattr(out, f, getattr(self, f)[keep])
        out.own = np.repeat(np.arange(len(at)), end - start)
        return out

    @staticmethod
    def of(rings: list) -> Rings:
        size = [len(r) for r in rings]
        starts = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
        return Rings(np.array([p["x"] for r in rings for p in r], np.int64), np.array([p["y"] for r in rings for p in r], np.int64), starts)

    def take(self, which: np.ndarray) -> Rings:
        """The rings of a mask, renumbered."""
        out = object.__new__(Rings)
        keep = which[self.own]
        out.n, out.area, out.box = int(which.sum()), self.area[which], self.box[which]
        for f in ("a", "b", "ya", "yb", "sign", "slope", "base"):
            setattr(out, f, getattr(self, f)[keep])
        out.own = (np.cumsum(which) - 1)[self.own[keep]]
        return out


#: Pairs of edges that are looked at together: what a cache holds.
MOST_EDGES = 1 << 15


def intersections(many: Rings, one: Rings, k: int = 0) -> np.ndarray:
    """Area shared by each ring of ``many`` and ring ``k`` of ``one``.

    Over the common span of two edges, the signed integral of the lower line;
    summed over all edge pairs it is the area of both. The lower line is the mean
    of both less half their gap, and the means cancel, for the signs of a ring's
    edges over any x add up to nothing: half the gaps remain.
    """
    own = one.edges(k)
    n, total = own.stop - own.start, np.zeros(many.n)
    if not n or not len(many.a):
        return total
    a, b, slope, base, sign = one.a[own], one.b[own], one.slope[own], one.base[own], one.sign[own]
    step = min(len(many.a), max(1, MOST_EDGES // n))
    lows, highs, some = np.empty((step, n)), np.empty((step, n)), np.empty((step, n), bool)
    for i in range(0, len(many.a), step):
        e = slice(i, min(len(many.a), i + step))
        lo, hi, met = (v[: e.stop - i] for v in (lows, highs, some))
        np.maximum(many.a[e, None], a, out=lo)
        np.minimum(many.b[e, None], b, out=hi)
        np.less(lo, hi, out=met)
        at = np.flatnonzero(met)
        if not len(at):
            continue
        g = at // n
        h = at - g * n
        g += i
        lo, hi = lo.ravel()[at], hi.ravel()[at]
        # How far the lines lie apart at both ends.
        d1, by = many.slope[g] - slope[h], many.base[g] - base[h]
        d0 = d1 * lo
        d0 += by
        d1 *= hi
        d1 += by
        hi -= lo
        # |d0| + |d1| halved, less |d0 * d1| / (|d0| + |d1|) where the lines cross.
        cross = np.minimum(d0 * d1, 0)
        gap = np.abs(d0, out=d0)
        gap += np.abs(d1, out=d1)
        cross /= np.maximum(gap, 1e-300, out=d1)
        gap *= 0.5
        gap += cross
        gap *= hi
        gap *= sign[h]
        gap *= many.sign[g]
        ring = many.own[g]
        sums = np.bincount(ring - ring[0], gap)
        total[ring[0] : ring[0] + len(sums)] += sums
    return np.maximum(total / -2, 0)


def distances(many: Rings, one: Rings, k: int = 0) -> np.ndarray:
    """Area Jaccard distance of each ring to ring ``k`` of ``one``."""
    shared = intersections(many, one, k)
    union = many.area + one.area[k] - shared
    return np.maximum(0.0, 1 - shared / np.where(union == 0, 1, union)) + 0.0  # no negative zero


def upper_bound(many: Rings, one: Rings, k: int = 0) -> np.ndarray:
    """A number that no similarity exceeds: from the areas and the overlap of the boxes."""
    a, b = many.area, one.area[k]
    m, o = many.box, one.box[k]
    over = np.maximum(0, np.minimum(m[:, 1], o[1]) - np.maximum(m[:, 0], o[0])) * np.maximum(0, np.minimum(m[:, 3], o[3]) - np.maximum(m[:, 2], o[2]))
    most = np.minimum(over, np.minimum(a, b))
    return most / np.maximum(a + b - most, 1e-300)


def cell_areas(rings: Rings, gx: np.ndarray, gy: np.ndarray) -> np.ndarray:
    """Area of each ring in each cell of the grid that these lines make (outer cells have no end): rings x cells, column by column."""
    lows, highs = np.concatenate([[-np.inf], gx]), np.concatenate([gx, [np.inf]])
    out = np.zeros((rings.n, len(lows), len(gy) + 1))
    for c, (x0, x1) in enumerate(zip(lows, highs, strict=True)):
        lo, hi = np.maximum(rings.a, x0), np.minimum(rings.b, x1)
        e = np.flatnonzero(hi > lo)
        lo, hi, own = lo[e], hi[e], rings.own[e]
        p0 = rings.ya[e] + (lo - rings.a[e]) * rings.slope[e]
        p1 = rings.ya[e] + (hi - rings.a[e]) * rings.slope[e]
        weight, below = rings.sign[e] * (hi - lo), 0.0
        for r, cut in enumerate([*gy, None]):
            if cut is None:
                mean = (p0 + p1) / 2
            else:  # the lower of the edge and the cut
                d0, d1 = p0 - cut, p1 - cut
                both = np.abs(d0) + np.abs(d1)
                gap = np.where(d0 * d1 >= 0, np.abs(d0 + d1) / 2, (d0 * d0 + d1 * d1) / (2 * np.where(both == 0, 1, both)))
                mean = (p0 + p1) / 4 + cut / 2 - gap / 2
            total = np.bincount(own, weight * mean, rings.n)
            out[:, c, r] = total - below
            below = total
    return out.reshape(rings.n, -1)


def plain_rings(rings: Rings) -> np.ndarray:
    """Whether a ring winds round each point once or not at all: w * (w - 1) is never negative for whole w, and sums to no area."""
    size = np.bincount(rings.own, minlength=rings.n)
    start = np.cumsum(size) - size
    square = np.zeros(rings.n)
    for part in blocks_of(size * size):
        n = size[part]
        own = np.repeat(np.arange(len(n)), n)
        first = spans(start[part], n)
        g, h = np.repeat(first, n[own]), spans(start[part][own], n[own])
        lo, hi = np.maximum(rings.a[g], rings.a[h]), np.minimum(rings.b[g], rings.b[h])
        some = hi > lo
        lo, hi, g, h, own = lo[some], hi[some], g[some], h[some], np.repeat(own, n[own])[some]
        d0 = rings.ya[g] + (lo - rings.a[g]) * rings.slope[g], rings.ya[h] + (lo - rings.a[h]) * rings.slope[h]
        d1 = rings.ya[g] + (hi - rings.a[g]) * rings.slope[g], rings.ya[h] + (hi - rings.a[h]) * rings.slope[h]
        a, b = d0[0] - d0[1], d1[0] - d1[1]
        both = np.abs(a) + np.abs(b)
        gap = np.where(a * b >= 0, np.abs(a + b) / 2, (a * a + b * b) / (2 * np.where(both == 0, 1, both)))
        square[part] = np.bincount(own, rings.sign[g] * rings.sign[h] * (hi - lo) * ((sum(d0) + sum(d1)) / 4 - gap / 2), len(n))
    return np.abs(square - rings.area) <= 1e-9 * rings.area + 1e-6


#: Columns and rows of cells, and of the groups of cells that are looked at first.
COARSE, ROUGH = 8, 4


class Grid:
    """Lines at quantiles of the queries' vertices: ``COARSE`` columns and rows, each cut in ``fine`` more."""

    def __init__(self, x: np.ndarray, y: np.ndarray, fine: int):
        self.fine, n = fine, COARSE * fine
        self.gx, self.gy = (np.quantile(v, np.arange(1, n) / n) if len(v) else np.zeros(n - 1) for v in (x, y))


class Celled:
    """Rings in order of area, with what they hold of each cell, rounded up; cells bound the area that two rings share."""

    def __init__(self, rings: Rings, grid: Grid):
        self.order = np.argsort(rings.area, kind="stable")
        self.rings = rings.pick(self.order)
        self.area, self.plain = self.rings.area, plain_rings(self.rings)
        self.odd = np.flatnonzero(~self.plain)
        n = COARSE * grid.fine
        cells = np.maximum(cell_areas(self.rings, grid.gx, grid.gy), 0)
        few = cells.reshape(rings.n, COARSE, grid.fine, COARSE, grid.fine).sum((2, 4))
        rough = few.reshape(rings.n, ROUGH, COARSE // ROUGH, ROUGH, COARSE // ROUGH).sum((2, 4))
        # Noise of the sums and of the short format, both far below what a bound could gain.
        self.cells, self.few, self.rough = ((c.reshape(rings.n, -1) + 1e-8 * self.area[:, None] + 1e-6).astype(np.float32) for c in (cells, few, rough))
        self.columns = np.ascontiguousarray(self.rough.T)

    def near(self, one: Celled, k: int, limit: float, among: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Places (by area) of the rings, or of those ``among`` (in order), that may lie within ``limit`` of ring ``k`` of ``one``, and the most they can be alike."""
        least, size = float(1 - limit - 1e-6), len(self.area)
        if not one.plain[k] or not np.isfinite(limit):
            least = -1.0
        a = one.area[k]
        lo, hi = (0, size) if least <= 0 else np.searchsorted(self.area, (a * least * (1 - 1e-9), a / least * (1 + 1e-9)))
        at = np.arange(lo, hi) if among is None else among[slice(*np.searchsorted(among, (lo, hi)))]
        if least > 0:
            if among is None or 4 * len(at) > hi - lo:
                theirs = one.rough[k][:, None]
                shared = [np.minimum(self.columns[:, i : min(hi, i + 2048)], theirs).sum(0) for i in range(lo, hi, 2048)]  # parts that a cache holds
                most = self._most(np.concatenate([np.zeros(0, np.float32), *shared]), self.area[lo:hi], a)
                at = at[(most if among is None else most[at - lo]) >= least]
            else:
                at = at[self._alike(self.rough, one.rough[k], at, a) >= least]
            at = at[self._alike(self.few, one.few[k], at, a) >= least]
        # Without a limit the numbers only tell which come first.
        cells, theirs = (self.cells, one.cells) if least > 0 else (self.few, one.few)
        most = self._alike(cells, theirs[k], at, a) if one.plain[k] else np.ones(len(at))
        keep = most >= least
        at, most = at[keep], most[keep]
        if len(self.odd):
            odd = self.odd if among is None else np.intersect1d(self.odd, among)
            rest = ~np.isin(at, odd)
            at, most = np.concatenate([at[rest], odd]), np.concatenate([most[rest], np.ones(len(odd))])
        return at, most

    def _alike(self, cells: np.ndarray, theirs: np.ndarray, at: np.ndarray, a: float) -> np.ndarray:
        """The most that the rings at these places can be alike one of area ``a``, by these cells."""
        most, step = np.ones(len(at)), (1 << 17) // cells.shape[1]
        for i in range(0, len(at), step):
            part = at[i : i + step]
            most[i : i + step] = self._most(np.minimum(cells[part], theirs).sum(1), self.area[part], a)
        return most

    def around(self, area: float, many: int, among: np.ndarray | None = None) -> np.ndarray:
        """Places of the ``many`` rings, or of those ``among``, next to an area."""
        at = int(np.searchsorted(self.area if among is None else self.area[among], area))
        lo = max(0, at - many // 2)
        return np.arange(lo, min(len(self.area), lo + many)) if among is None else among[lo : lo + many]

    @staticmethod
    def _most(shared: np.ndarray, areas: np.ndarray, a: float) -> np.ndarray:
        s = np.minimum(shared.astype(float) * (1 + 1e-4), np.minimum(areas, a))
        return s / (areas + a - s)
