"""Document fingerprints from statistically improbable byte windows.

Every 64-byte window of a text has an entropy, in one of 1,000 classes. A class's
rarity is its rank by frequency among the windows of the whole corpus
(``fit_rarity``; one pass, 1,000 sums). A window is a feature if it is the rarest
(leftmost of ties) in at least ``POPULAR`` of the 64 neighbourhoods it lies in.
Feature hashes go, in text order, into a chain of 2,048-bit Bloom filters, five
bits a feature and at most 160 features a filter. Two chains are compared filter
by filter: the bits they share, less those that chance alone gives, over the most
they could share; each filter of the shorter chain takes its best match, and the
mean is the likeness (0 to 1).

Defined cases: a text with fewer than 8 features adds its distinct 8-byte windows,
one of fewer than 8 bytes itself; two empty texts are alike 1.0; null counts as empty; rows that repeat a doc_id follow each other in the order of
their texts; a null doc_id sorts first; extra columns are ignored; an empty table
gives no rows; the next of a sole document is itself.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapesig.llm.common import block_count, offsets_of, rows_of, text_bytes
from shapesig.llm.kernels import mixed, xxh64_spans

WINDOW, CLASSES, NEIGHBOURS, POPULAR = 64, 1000, 64, 16
BLOOM_BYTES, PER_FILTER, HASHES = 256, 160, 5
_XLOG = np.concatenate([[0.0], np.arange(1, WINDOW + 2) * np.log2(np.arange(1, WINDOW + 2))]).astype(np.float32)
CHUNK = 1 << 18
FEW = 8


def entropy_classes(raw: np.ndarray) -> np.ndarray:
    """Entropy class (0 .. CLASSES-1) of each window of ``raw``, an array of bytes."""
    n = len(raw) - WINDOW + 1
    if n <= 0:
        return np.zeros(0, np.int16)
    if n > CHUNK:
        return np.concatenate([entropy_classes(raw[a : min(len(raw), a + CHUNK + WINDOW - 1)]) for a in range(0, n, CHUNK)])
    # Equal bytes among the 63 before and the 63 after each place.
    before = np.zeros(len(raw), np.uint8)
    after = np.zeros(len(raw), np.uint8)
    for k in range(1, WINDOW):
        same = (raw[k:] == raw[:-k]).view(np.uint8)
        before[k:] += same
        after[:-k] += same
    counts = np.bincount(raw[:WINDOW], minlength=256)
    total = np.empty(n, np.float64)
    total[0] = _XLOG[counts].sum()
    # Sliding by one: the first byte leaves, then the next one enters the 63 that stay.
    out = after[: n - 1].astype(np.int16) + 1
    into = before[WINDOW:].astype(np.int16)
    total[1:] = (_XLOG[into + 1] - _XLOG[into]) - (_XLOG[out] - _XLOG[out - 1])
    h = np.log2(WINDOW) - np.cumsum(total) / WINDOW
    return np.clip(h * ((CLASSES - 1) / np.log2(WINDOW)) + 1e-6, 0, CLASSES - 1).astype(np.int16)


def _selected(classes: np.ndarray, rarity: np.ndarray) -> np.ndarray:
    """Starts of the selected windows of one text: those that are rarest in enough neighbourhoods."""
    n = len(classes)
    if n == 0:
        return np.zeros(0, np.int64)
    width = min(NEIGHBOURS, n)
    low = (rarity[classes] << 40) | np.arange(n)
    span = 1
    while span * 2 <= width:
        low = np.minimum(low[:-span], low[span:])
        span *= 2
    if span < width:
        low = np.minimum(low[: len(low) - (width - span)], low[width - span :])
    votes = np.bincount(low & ((1 << 40) - 1), minlength=n)
    return np.flatnonzero(votes >= min(POPULAR, len(low)))


Digest = tuple[bytes, list[int]]


def digests(texts: list[bytes], rarity: np.ndarray) -> list[Digest]:
    """For each text the chain of Bloom filters as bytes, and the features in each."""
    ends = np.cumsum([len(t) for t in texts])
    raw = np.frombuffer(b"".join(texts) + bytes(8), np.uint8)
    classes = entropy_classes(raw[: ends[-1]]) if len(texts) else np.zeros(0, np.int16)
    at = [_selected(classes[e - len(t) : max(e - len(t), e - WINDOW + 1)], rarity) + (e - len(t)) for t, e in zip(texts, ends.tolist(), strict=True)]
    flat = np.concatenate(at) if at else np.zeros(0, np.int64)
    every = xxh64_spans(raw, flat, np.full(len(flat), WINDOW, np.int64), 7)
    out, done = [], 0
    for text, starts in zip(texts, at, strict=True):
        h = every[done : done + len(starts)]
        done += len(starts)
        if len(h):
            _, first = np.unique(h, return_index=True)
            h = h[np.sort(first)]
        if len(h) < FEW:  # a short or monotonous text: its small windows serve too
            small = np.ndarray((max(0, len(text) - 7),), "<u8", text, 0, (1,)) if len(text) >= 8 else np.array([xxhash.xxh64_intdigest(text, 7)], np.uint64)
            _, first = np.unique(small, return_index=True)
            h = np.concatenate([h, mixed(small[np.sort(first)] + np.uint64(7))])
        where = np.arange(len(h)) // PER_FILTER
        bits = np.zeros((int(where[-1]) + 1, BLOOM_BYTES * 8), bool)
        for k in range(HASHES):
            bits[where, (h >> np.uint64(11 * k)).astype(np.int64) & 2047] = True
        out.append((np.packbits(bits, axis=1).tobytes(), np.bincount(where).tolist()))
    return out


def likeness(a: Digest, b: Digest) -> float:
    """Mean over the shorter chain of each filter's best normalised overlap; the same either way round."""
    if a[0] == b[0]:
        return 1.0
    if (len(a[1]), a[0]) > (len(b[1]), b[0]):
        a, b = b, a
    x, y = (np.frombuffer(s[0], np.uint64).reshape(-1, BLOOM_BYTES // 8) for s in (a, b))
    px, py = (np.bitwise_count(v).sum(1).astype(np.float64) for v in (x, y))
    total = 0.0
    for i in range(len(x)):
        both = np.bitwise_count(x[i] & y).sum(1)
        chance = px[i] * py / (BLOOM_BYTES * 8)
        cut = chance + 0.05 * (np.minimum(px[i], py) - chance)
        most = np.maximum(np.minimum(px[i], py) - cut, 1e-9)
        total += float(np.clip((both - cut) / most, 0, 1).max())
    return total / len(x)


def written(d: Digest) -> str:
    """The fingerprint as text: features of each filter, then the filters in hex."""
    return ".".join(map(str, d[1])) + ":" + d[0].hex()


def fit_rarity(docs: DataFrame) -> np.ndarray:
    """Rank of each entropy class, rarest first, by its windows in all documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CLASSES, np.int64)
        for batch in batches:
            for part in rows_of(batch, "text", CHUNK):
                texts = pc.fill_null(part.column(0), "")
                off = offsets_of(texts)
                raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[off[0] : off[-1]]
                classes = entropy_classes(raw)
                whole = np.zeros(len(raw) + 1, np.int64)  # windows that end in the text they begin in
                np.add.at(whole, off[:-1] - off[0], 1)
                np.add.at(whole, np.maximum(off[:-1], off[1:] - WINDOW + 1) - off[0], -1)
                total += np.bincount(classes[np.cumsum(whole)[: len(classes)] > 0], minlength=CLASSES)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(CLASSES)), pa.array(total)], ["class", "n"])

    sums = docs.select("text").mapInArrow(run, "class long, n long").groupBy("class").agg(F.sum("n").alias("n")).collect()
    n = np.zeros(CLASSES, np.int64)
    for r in sums:
        n[r["class"]] = r["n"]
    rank = np.empty(CLASSES, np.int64)
    rank[np.lexsort((np.arange(CLASSES), n))] = np.arange(CLASSES)
    return rank


def in_order(docs: DataFrame, parts: int) -> DataFrame:
    """Documents dealt into ranges of doc_id; a copy of each range's first is added, marked, to the range before.

    The last range gets the first of all. What comes to the driver is the cut
    ids and the first id of each range, not more than ``parts`` of them.
    """
    key = F.coalesce("doc_id", F.lit(-(1 << 63)))
    ids = docs.select(key.alias("id"))
    got = ids.agg(F.percentile_approx("id", [i / parts for i in range(1, parts)], 10_000).alias("c")).first()["c"] if parts > 1 else []
    cuts = np.array(sorted(set(got or [])), np.int64)

    @F.pandas_udf("int")
    def range_of(id_: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(cuts, id_.to_numpy(np.int64), "right").astype(np.int32))

    firsts = sorted((r["p"], r["f"]) for r in ids.select("id", range_of("id").alias("p")).groupBy("p").agg(F.min("id").alias("f")).collect())
    before = pd.Series({f: firsts[i - 1][0] for i, (_, f) in enumerate(firsts)}, dtype="float64")

    @F.pandas_udf("array<int>")
    def spots(id_: pd.Series) -> pd.Series:
        own = np.searchsorted(cuts, id_.to_numpy(np.int64), "right")
        also = before.reindex(id_.to_numpy(np.int64)).to_numpy()
        return pd.Series([[int(a)] if np.isnan(b) else [int(a), -int(b) - 1] for a, b in zip(own, also, strict=True)])

    spread = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.explode(spots(key)).alias("s"))
    return spread.select("doc_id", "text", F.when(F.col("s") < 0, -F.col("s") - 1).otherwise(F.col("s")).alias("p"), (F.col("s") < 0).alias("closing"))


def edited(text: str, following: str) -> str:
    """The text with its last half replaced by the first as many code points of the following one."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def compare(docs: DataFrame, parts: int | None = None, rarity: np.ndarray | None = None) -> DataFrame:
    """Per document: fingerprints of it and of its edited text, and likeness to that text and to the next document."""
    n = parts or block_count(text_bytes(docs), most=4096)
    ranks = fit_rarity(docs) if rarity is None else rarity
    rows = in_order(docs, n).repartition(n, "p").sortWithinPartitions("p", "closing", F.col("doc_id").asc_nulls_first(), "text")
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]

    def pairs(chain: list[tuple]) -> pa.RecordBatch:
        """Rows of all documents of the chain but the last, which follows the one before it."""
        texts = [t for _, t in chain]
        own = digests([t.encode() for t in texts], ranks)
        others = [edited(a, b).encode() for a, b in zip(texts, texts[1:], strict=False)]
        changed = digests(others, ranks)
        out = [(i, len(t), hashlib.sha256(o).hexdigest(), written(d), written(c), likeness(d, c), likeness(d, f)) for (i, t), o, d, c, f in zip(chain, others, own, changed, own[1:], strict=False)]
        return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chain: list[tuple] = []
        size = 0
        for batch in batches:
            for part in rows_of(batch, "text"):
                for i, text, closing in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(3).to_pylist(), strict=True):
                    if closing and not chain:
                        continue  # a repeated first row of the next range
                    chain.append((i, text))
                    size += len(text)
                    if len(chain) > 1 and (closing or size > CHUNK):
                        yield pairs(chain)
                        chain = [] if closing else chain[-1:]
                        size = 0

    return rows.mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
