"""Repeated passages, found through difference-cover anchors.

A document's anchors are hashes of 7 words that start at places whose number
modulo 7 is in {1, 2, 4}. Any two of the residues 0..6 shift by the same amount
into that set, so two equal windows of 13 words, wherever they start, hold an
equal anchor at the same distance. Three exchanges follow, none of which moves
an anchor's documents:

1. Documents are dealt into blocks by hash of doc_id (the one exchange of texts;
   the later steps reuse it). Each block sends every bucket of anchor hashes one
   packed blob: its distinct anchors, 4 bytes each beside the bucket's number,
   and a bit that says whether two of its documents hold it.
2. A bucket answers each blob with a bit for every anchor: held by two documents
   or more. Windows around such anchors are the extensions; their 128-bit hashes
   and smallest doc_id in the block go out packed in the same way.
3. A bucket of windows answers with a bit: a smaller doc_id has it elsewhere.
   The block removes the covered words and digests what is left.

A passage that a third of all documents share is one entry of each block, so no
group of documents meets in one task and no pairs are made. An anchor that falsely
matches only adds windows to step 2; windows are compared by 128 bits.

Defined cases: null text has no words; fewer words than a window are kept whole;
ties in doc_id are not smaller than each other; a null doc_id counts as larger
than all others; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapesig.llm.common import block_count, text_bytes
from shapesig.llm.kernels import Words, mixed, runs

PERIOD, COVER = 7, (1, 2, 4)  # fixed values: a perfect difference set
WINDOW = 13
ANCHOR = WINDOW - PERIOD + 1
BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93)
NO_ID = np.iinfo(np.int64).max


class _Block:
    """One block's words with anchors, in an order that depends on its rows only."""

    def __init__(self, rows: pa.Table, buckets: int):
        ids = rows["doc_id"].combine_chunks()
        self.null = np.asarray(ids.is_null())
        self.ids = np.where(self.null, NO_ID, np.asarray(ids.fill_null(0))).astype(np.int64)
        text = rows["text"].combine_chunks()
        self.words = w = Words(text)
        self.hash = w.hashes()
        self.n = len(self.hash)
        self.buckets = buckets
        self.place = np.arange(self.n) - np.repeat(w.first[:-1], w.per_doc)
        self.left = np.repeat(w.per_doc, w.per_doc) - self.place  # words from here to the text's end

    def anchors(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places of anchors, their bucket and their 32 bits within it."""
        h = runs(self.hash, ANCHOR, BASES[0])
        m = len(h)
        ok = (self.left[:m] >= ANCHOR) & np.isin(self.place[:m] % PERIOD, COVER) & (np.repeat(self.words.per_doc, self.words.per_doc)[:m] >= WINDOW)
        at = np.flatnonzero(ok)
        return at, *_split(h[at], self.buckets)


def _split(h: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    return ((h >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64), (h & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def _blobs(bucket: np.ndarray, *columns: np.ndarray) -> Iterator[tuple]:
    """(bucket, bytes of each column) for rows sorted by bucket."""
    edges = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1], [True]])) if len(bucket) else []
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        yield int(bucket[a]), *(c[a:b] for c in columns)


def _groups(sorted_key: np.ndarray) -> np.ndarray:
    """Starts of runs of equal keys."""
    return np.flatnonzero(np.concatenate([[True], sorted_key[1:] != sorted_key[:-1]])) if len(sorted_key) else np.zeros(0, np.int64)


def _anchor_groups(b: _Block) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Anchor places in order of their distinct keys; starts of groups; bucket, bits and 'in two documents' of each."""
    at, bucket, bits = b.anchors()
    key = (bucket.astype(np.uint64) << np.uint64(32)) | bits
    order = np.argsort(key, kind="stable")
    at, key = at[order], key[order]
    starts = _groups(key)
    doc = b.words.doc[at]
    many = np.maximum.reduceat(doc, starts) != np.minimum.reduceat(doc, starts) if len(starts) else np.zeros(0, bool)
    head = key[starts]
    return at, starts, (head >> np.uint64(32)).astype(np.int64), (head & np.uint64(0xFFFFFFFF)).astype(np.uint32), many


def _candidates(b: _Block, answers: dict[int, bytes]) -> np.ndarray:
    """Starts of windows that hold an anchor which two documents have."""
    at, starts, bucket, bits, _ = _anchor_groups(b)
    shared = np.concatenate([_bits(answers[k], len(c)) for k, c in _blobs(bucket, bits)]) if len(starts) else np.zeros(0, bool)
    hit = at[np.repeat(shared, np.diff(np.append(starts, len(at))))] if len(starts) else at
    # A window starts up to PERIOD - 1 places before its anchor.
    near = np.zeros(b.n + 1, np.int64)
    np.add.at(near, np.maximum(hit - (PERIOD - 1), b.words.first[b.words.doc[hit]]), 1)
    np.add.at(near, hit + 1, -1)
    return np.flatnonzero((np.cumsum(near[:-1]) > 0) & (b.left >= WINDOW)) if b.n else np.zeros(0, np.int64)


def _window_groups(b: _Block, starts_at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Window starts in order of distinct windows; group starts; bucket, both hashes and smallest id of each."""
    h1, h2 = (runs(b.hash, WINDOW, x)[starts_at] if b.n >= WINDOW else np.zeros(0, np.uint64) for x in BASES[1:])
    bucket = (h1 % np.uint64(b.buckets)).astype(np.int64)
    order = np.lexsort((h2, h1, bucket))
    at, h1, h2, bucket = starts_at[order], h1[order], h2[order], bucket[order]
    new = np.ones(len(at), bool)
    new[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
    g = np.flatnonzero(new)
    low = np.minimum.reduceat(b.ids[b.words.doc[at]], g) if len(g) else np.zeros(0, np.int64)
    return at, g, bucket[g], h1[g], h2[g], low


def _bits(blob: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(blob, np.uint8), count=n).astype(bool)


def _planes(values: np.ndarray) -> bytes:
    """Bytes of equal rank together: the high ones are mostly zero and compress away."""
    return np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes()


def _unplanes(blob: bytes, kind: type) -> np.ndarray:
    width = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(blob, np.uint8).reshape(width, -1).T).view(kind).reshape(-1)


ASKED = pa.schema([("bucket", pa.int64()), ("block", pa.int64()), ("keys", pa.binary()), ("more", pa.binary())])
ANSWER = pa.schema([("block", pa.int64()), ("step", pa.int32()), ("bucket", pa.int64()), ("bits", pa.binary())])
RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())])
_DDL = {id(ASKED): "bucket long, block long, keys binary, more binary", id(ANSWER): "block long, step int, bucket long, bits binary", id(RESULT): "doc_id long, n_words long, n_removed long, kept_sha256 string"}


def _answers(rows: pa.Table, step: int) -> dict[int, bytes]:
    return {b: x for s, b, x in zip(*(rows[c].to_pylist() for c in ("step", "bucket", "bits")), strict=True) if s == step}


def remove_repeats(docs: DataFrame, blocks: int | None = None, with_text: bool = False) -> DataFrame:
    """Per document: its words, how many are removed, and the digest (or, too, the text) of what is left."""
    n = blocks or block_count(text_bytes(docs))
    dealt = docs.select("doc_id", "text", F.pmod(F.xxhash64("doc_id"), F.lit(n)).alias("block"))

    def ask_anchors(rows: pa.Table) -> pa.Table:
        b = _Block(rows, n)
        _, starts, bucket, bits, many = _anchor_groups(b)
        out = [(k, rows["block"][0].as_py(), _planes(x), np.packbits(m).tobytes()) for k, x, m in _blobs(bucket, bits, many)]
        return _made(out, ASKED)

    def answer_anchors(rows: pa.Table) -> pa.Table:
        keys = [_unplanes(x, np.uint32) for x in rows["keys"].to_pylist()]
        many = [_bits(x, len(k)) for x, k in zip(rows["more"].to_pylist(), keys, strict=True)]
        every = np.concatenate(keys)
        held, place, seen = np.unique(every, return_inverse=True, return_counts=True)
        shared = seen > 1
        np.logical_or.at(shared, place, np.concatenate(many))
        return _reply(rows, keys, shared[place], 1)

    def ask_windows(key: tuple, rows: pa.Table, replies: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return _made([], ASKED)
        b = _Block(rows, n)
        _, _, bucket, h1, h2, low = _window_groups(b, _candidates(b, _answers(replies, 1)))
        return _made([(k, key[0].as_py(), x.tobytes() + y.tobytes(), _planes(z)) for k, x, y, z in _blobs(bucket, h1, h2, low)], ASKED)

    def answer_windows(rows: pa.Table) -> pa.Table:
        parts = [np.frombuffer(x, np.uint64).reshape(2, -1) for x in rows["keys"].to_pylist()]
        low = np.concatenate([_unplanes(x, np.int64) for x in rows["more"].to_pylist()])
        h1, h2 = np.concatenate(parts, axis=1)
        order = np.lexsort((h2, h1))
        new = np.ones(len(order), bool)
        new[1:] = (h1[order][1:] != h1[order][:-1]) | (h2[order][1:] != h2[order][:-1])
        g = np.flatnonzero(new)
        least = np.empty(len(order), np.int64)
        least[order] = np.repeat(np.minimum.reduceat(low[order], g), np.diff(np.append(g, len(order))))
        return _reply(rows, [x[0] for x in parts], least < low, 2)

    def finish(key: tuple, rows: pa.Table, replies: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return _made([], out_schema)
        b = _Block(rows, n)
        at, g, bucket, h1, _, low = _window_groups(b, _candidates(b, _answers(replies, 1)))
        said = _answers(replies, 2)
        elsewhere = np.concatenate([_bits(said[k], len(x)) for k, x in _blobs(bucket, h1)]) if len(g) else np.zeros(0, bool)
        times = np.diff(np.append(g, len(at)))
        gone = at[np.repeat(elsewhere, times) | (b.ids[b.words.doc[at]] > np.repeat(low, times))]
        cover = np.zeros(b.n + 1, np.int64)
        np.add.at(cover, gone, 1)
        np.add.at(cover, gone + WINDOW, -1)
        covered = np.cumsum(cover[:-1]) > 0
        out, w = [], b.words
        removed = np.diff(np.concatenate([[0], np.cumsum(covered)])[w.first])
        for i in range(w.n_docs):
            if removed[i]:
                keep = np.flatnonzero(~covered[w.first[i] : w.first[i + 1]]) + w.first[i]
                left = b" ".join(w.buf[s : s + z].tobytes() for s, z in zip(w.start[keep].tolist(), w.size[keep].tolist(), strict=True))
            else:
                left = w.text(i)
            out.append((None if b.null[i] else int(b.ids[i]), int(w.per_doc[i]), int(removed[i]), hashlib.sha256(left).hexdigest(), *([left.decode()] if with_text else [])))
        return _made(out, out_schema)

    out_schema = RESULT.append(pa.field("kept", pa.string())) if with_text else RESULT
    asked = dealt.groupBy("block").applyInArrow(ask_anchors, _DDL[id(ASKED)])
    first = asked.groupBy("bucket").applyInArrow(answer_anchors, _DDL[id(ANSWER)])
    windows = dealt.groupBy("block").cogroup(first.groupBy("block")).applyInArrow(ask_windows, _DDL[id(ASKED)])
    second = windows.groupBy("bucket").applyInArrow(answer_windows, _DDL[id(ANSWER)])
    both = first.unionByName(second)
    return dealt.groupBy("block").cogroup(both.groupBy("block")).applyInArrow(finish, _DDL[id(RESULT)] + (", kept string" if with_text else ""))


def _made(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    columns = list(zip(*rows, strict=True)) if rows else [[]] * len(schema)
    return pa.table([pa.array(list(c), f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def _reply(rows: pa.Table, keys: list[np.ndarray], flag: np.ndarray, step: int) -> pa.Table:
    ends = np.cumsum([len(k) for k in keys])
    bits = [np.packbits(x).tobytes() for x in np.split(flag, ends[:-1])]
    return pa.table([rows["block"], pa.array([step] * len(keys), pa.int32()), rows["bucket"], pa.array(bits, pa.binary())], schema=ANSWER)
