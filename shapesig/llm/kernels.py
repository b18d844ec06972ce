"""Vectorised byte kernels: word spans, normalised words and XXH64 over many spans at once."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

from shapesig.llm.common import offsets_of

IS_SPACE = np.zeros(256, bool)
IS_SPACE[[32, *range(9, 14)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

# Fixed values of the XXH64 definition.
P1, P2, P3, P4, P5 = (np.uint64(x) for x in (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261))
_U = np.uint64


def _rot(x: np.ndarray, r: int) -> np.ndarray:
    return (x << _U(r)) | (x >> _U(64 - r))


def _round(acc: np.ndarray, lane: np.ndarray) -> np.ndarray:
    return _rot(acc + lane * P2, 31) * P1


def xxh64_spans(buf: np.ndarray, start: np.ndarray, length: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of ``buf[start:start+length]`` for all spans; ``buf`` must carry 8 spare bytes at its end."""
    with np.errstate(over="ignore"):
        u8 = np.ndarray((max(0, len(buf) - 7),), "<u8", buf, 0, (1,))
        u4 = np.ndarray((max(0, len(buf) - 3),), "<u4", buf, 0, (1,))
        h = np.full(len(start), _U(seed) + P5)
        at = start.copy()
        if len(big := np.flatnonzero(length >= 32)):
            v = [np.full(len(big), _U(seed) + x) for x in (P1 + P2, P2, _U(0), _U(0) - P1)]
            live, stripes, p = np.arange(len(big)), np.minimum(length[big], 2048) >> 5, start[big].copy()
            for s in range(int(stripes.max())):
                live = live[stripes[live] > s]
                for k in range(4):
                    v[k][live] = _round(v[k][live], u8[p[live] + 8 * k])
                p[live] += 32
            acc = _rot(v[0], 1) + _rot(v[1], 7) + _rot(v[2], 12) + _rot(v[3], 18)
            for x in v:
                acc = (acc ^ _round(_U(0), x)) * P1 + P4
            h[big], at[big] = acc, p
        h += length.astype(np.uint64)
        rest = length & 31
        for j in range(3):
            if not len(live := np.flatnonzero(rest >> 3 > j)):
                break
            x = h[live] ^ _round(_U(0), u8[at[live]])
            h[live] = _rot(x, 27) * P1 + P4
            at[live] += 8
        if len(live := np.flatnonzero(rest & 4)):
            x = h[live] ^ (u4[at[live]].astype(np.uint64) * P1)
            h[live] = _rot(x, 23) * P2 + P3
            at[live] += 4
        for j in range(3):
            if not len(live := np.flatnonzero((rest & 3) > j)):
                break
            x = h[live] ^ (buf[at[live]].astype(np.uint64) * P5)
            h[live] = _rot(x, 11) * P1
            at[live] += 1
        h ^= h >> _U(33)
        h *= P2
        h ^= h >> _U(29)
        h *= P3
        h ^= h >> _U(32)
    for i in np.flatnonzero(length > 2048 + 31):  # rare long spans: the library streams them
        h[i] = xxhash.xxh64_intdigest(buf[start[i] : start[i] + length[i]].tobytes(), seed)
    return h


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser, so that any bits of a combined hash are usable."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(33))) * P2
        x = (x ^ (x >> _U(29))) * P3
        return x ^ (x >> _U(32))


def ragged(at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Indices of all spans, one after another."""
    ends = np.cumsum(size)
    total = int(ends[-1]) if len(ends) else 0
    return np.arange(total) - np.repeat(ends - size, size) + np.repeat(at, size)


class Words:
    """Words of many texts, each joined by one space: bytes ``buf``, spans, and first word of each text."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        texts = pc.fill_null(texts, "")
        off = offsets_of(texts)
        raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[off[0] : off[-1]] if len(texts) and texts.buffers()[2] else np.zeros(0, np.uint8)
        off = off - off[0]
        self.n_docs = len(texts)
        space = IS_SPACE[raw]
        first = np.zeros(len(raw) + 1, bool)
        first[off] = True
        solid = ~space
        before = np.empty(len(raw), bool)
        before[:1] = True
        before[1:] = space[:-1]
        starts = np.flatnonzero(solid & (before | first[:-1]))
        after = np.empty(len(raw), bool)
        after[-1:] = True
        after[:-1] = space[1:]
        ends = np.flatnonzero(solid & (after | first[1:])) + 1
        self.first = np.searchsorted(starts, off)  # first word of each text, and the number of all
        self.per_doc = np.diff(self.first)
        doc = np.repeat(np.arange(self.n_docs), self.per_doc)
        # New places: the words' bytes and one space after each word but a text's last.
        size = ends - starts
        gap = np.ones(len(starts), np.int64)
        gap[self.first[1:][self.per_doc > 0] - 1] = 0
        self.start = np.concatenate([[0], np.cumsum(size + gap)])[:-1].astype(np.int64) if len(starts) else np.zeros(0, np.int64)
        self.size, self.doc = size, doc
        total = int((size + gap).sum())
        buf = np.full(total + 8, 32, np.uint8)
        buf[total:] = 0
        place = np.ones(total, bool)
        place[(self.start + size)[gap == 1]] = False
        kept = raw[solid]
        buf[:total][place] = LOWER[kept] if lower else kept
        self.buf = buf

    def hashes(self, seed: int = 42) -> np.ndarray:
        return xxh64_spans(self.buf, self.start, self.size.astype(np.int64), seed)

    def text(self, doc: int) -> bytes:
        """The words of a text, joined by one space."""
        a, b = self.first[doc], self.first[doc + 1]
        return self.buf[self.start[a] : self.start[b - 1] + self.size[b - 1]].tobytes() if b > a else b""


def runs(hashes: np.ndarray, width: int, base: int) -> np.ndarray:
    """Hash of ``width`` consecutive word hashes from each place on (the last ``width - 1`` have none)."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        out, b = np.zeros(n, np.uint64), _U(base)
        for k in range(width):
            out = out * b + hashes[k : k + n]
    return mixed(out)
