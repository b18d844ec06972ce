"""Near duplicates by SimHash and the general pigeonhole principle.

Fingerprints are 64 bits over XXH64 of 3-word shingles. Distinct fingerprints
are the nodes. Bits are grouped into partitions by their agreement in the whole
table, each partition i gets a threshold t_i (-1: unused) with
``sum(t) = radius - partitions + 1``, and any two fingerprints within the radius
then agree within t_i bits on some partition. A dynamic program picks the
thresholds, and a comparison over partition counts picks the partitioning, for
least estimated cost of probes and candidates. Fingerprints are indexed by each
used partition's bits, probed with all patterns within its threshold, and
verified by the full distance.

A bucket with more than ``DENSE`` fingerprints is not paired out: its members and
those that probe it are linked through the 65 points within one bit of each (two
fingerprints share such a point exactly when they differ in 2 bits or fewer),
of which a point has 65 fingerprints at most. That is linear and loses no link.

Defined cases: null text counts as empty; no words: fingerprint zero, linked like
any other; fewer than 3 words: the whole sequence is one shingle; equal texts
share a node; rows that repeat a doc_id are each returned, a null doc_id gets
its component's least id; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapesig.llm.common import cut, in_arrow, rows_of
from shapesig.llm.graph import components
from shapesig.llm.kernels import Words, xxh64_spans

BITS, RADIUS, SHINGLE, DENSE = 64, 2, 3, 64


def fingerprints_of(texts: pa.Array, shingle: int = SHINGLE) -> np.ndarray:
    """Unsigned SimHash fingerprint of each text."""
    w = Words(texts, lower=True)
    each = np.where(w.per_doc >= shingle, w.per_doc - shingle + 1, (w.per_doc > 0).astype(np.int64))
    doc = np.repeat(np.arange(w.n_docs), each)
    begin = np.concatenate([[0], np.cumsum(each)])
    first = w.first[:-1][doc] + np.arange(len(doc)) - begin[:-1][doc]
    last = np.minimum(first + shingle, w.first[1:][doc]) - 1
    out = np.zeros(w.n_docs, np.uint64)
    if not len(doc):
        return out
    h = xxh64_spans(w.buf, w.start[first], (w.start[last] + w.size[last] - w.start[first]).astype(np.int64))
    some = np.flatnonzero(each)
    bits = np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    ones = np.add.reduceat(bits, begin[:-1][some], axis=0, dtype=np.int64)
    out[some] = np.packbits(ones * 2 > each[some, None], axis=1, bitorder="little").view("<u8").reshape(-1)
    return out


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp) with the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in rows_of(batch, "text", 2 << 20):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fingerprints_of(part.column(1)).view(np.int64))], ["doc_id", "fp"])

    return in_arrow(docs.select("doc_id", "text"), run, "doc_id long, fp long")


# ---- plan of the search


@dataclass(frozen=True)
class Part:
    """Bits of one partition, its threshold, and the patterns to probe with."""

    bits: tuple[int, ...]
    radius: int

    @property
    def mask(self) -> int:
        return sum(1 << b for b in self.bits)

    @property
    def flips(self) -> list[int]:
        return [sum(1 << b for b in c) for r in range(self.radius + 1) for c in itertools.combinations(self.bits, r)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def bit_counts(nodes: DataFrame) -> tuple[int, np.ndarray]:
    """Number of fingerprints and, for each two bits, how many set both: from all rows, 64 sums per task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros((BITS, BITS), np.int64), 0
        for batch in batches:
            x = np.unpackbits(np.asarray(batch.column(0)).astype("<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float32)
            for part in np.array_split(x, max(1, len(x) // 100_000)):
                total += (part.T @ part).astype(np.int64)
            n += len(x)
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([[n], total.reshape(-1)]).tolist()])], ["sums"])

    sums = in_arrow(nodes.select("fp"), run, "sums array<long>").select(F.posexplode("sums").alias("at", "v")).groupBy("at").agg(F.sum("v").alias("v")).collect()
    flat = np.zeros(1 + BITS * BITS, np.int64)
    for r in sums:
        flat[r["at"]] = r["v"]
    return int(flat[0]), flat[1:].reshape(BITS, BITS)


def plan(n: int, both: np.ndarray, radius: int = RADIUS, most_parts: int = 6, share: float = 1.0, copies: int = 1) -> list[Part]:
    """The partitions and thresholds of least estimated cost for a self-join of ``n`` fingerprints.

    ``share`` is the share of all pairs that a further key lets meet, ``copies``
    the rows that it makes of each probe.
    """
    n = max(1, n)  # an empty table costs no probes, which must not make them many
    p = both / n
    one = np.diag(p)
    agree = one**2 + (1 - one) ** 2
    cells = [p, one[:, None] - p, one[None, :] - p, 1 - one[:, None] - one[None, :] + p]
    pair = sum(np.maximum(c, 0) ** 2 for c in cells)  # chance that two fingerprints agree on both bits
    lift = np.log(np.maximum(pair, 1e-12)) - np.log(np.maximum(np.outer(agree, agree), 1e-12))
    best: tuple[float, list[Part]] = (math.inf, [])
    for m in range(1, most_parts + 1):
        groups = _grouped(lift, agree, m)
        need = radius - m + 1
        costs = [{t: _cost(n, g, t, pair, agree, share, copies) for t in range(-1, radius + 1)} for g in groups]
        state: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
        for c in costs:
            nxt: dict[int, tuple[float, list[int]]] = {}
            for s, (v, ts) in state.items():
                for t, x in c.items():
                    if s + t not in nxt or v + x < nxt[s + t][0]:
                        nxt[s + t] = (v + x, [*ts, t])
            state = nxt
        v, ts = state.get(need, (math.inf, []))
        if v < best[0]:
            best = (v, [Part(tuple(g), t) for g, t in zip(groups, ts, strict=True) if t >= 0])
    return best[1]


def _grouped(lift: np.ndarray, agree: np.ndarray, m: int) -> list[list[int]]:
    """Bits in ``m`` groups of near-equal size; a group grows by the bit that most agrees with its members."""
    free = set(range(BITS))
    out = []
    for k in range(m):
        size = (BITS - sum(map(len, out))) // (m - k)
        group = [max(free, key=lambda b: (agree[b], -b))]
        free.discard(group[0])
        while len(group) < size:
            b = max(free, key=lambda b: (float(lift[b, group].max()), -b))
            group.append(b)
            free.discard(b)
        out.append(sorted(group))
    return out


def _cost(n: int, group: list[int], t: int, pair: np.ndarray, agree: np.ndarray, share: float, copies: int) -> float:
    """Probes and expected candidates within ``t`` bits, the bits taken as a chain of their strongest agreements."""
    if t < 0:
        return 0.0
    poly = np.zeros(t + 1)
    poly[0] = 1.0
    done: list[int] = []
    for b in group:
        a = float(max((pair[b, c] / max(agree[c], 1e-12) for c in done), default=agree[b]))
        a = min(1.0, max(a, 1e-9))
        poly = poly * a + np.concatenate([[0.0], poly[:-1]]) * (1 - a)
        done.append(b)
    probes = sum(math.comb(len(group), r) for r in range(t + 1))
    return n * copies * probes + 0.5 * n * n * share * float(poly.sum())


def _flip(parts: list[Part]) -> Column:
    return F.array(*(F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(F.lit(signed(p.mask))).bitwiseXOR(F.lit(signed(x))).alias("key")) for i, p in enumerate(parts) for x in p.flips))


def links(nodes: DataFrame, radius: int = RADIUS, dense: int = DENSE) -> DataFrame:
    """Edges (a, b) that connect all fingerprints within ``radius`` bits of each other (2, when buckets are dense)."""
    n, both = bit_counts(nodes)
    parts = plan(n, both, radius) or [Part(tuple(range(BITS)), radius)]
    held = nodes.select("fp", F.explode(F.array(*(F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(F.lit(signed(p.mask))).alias("key")) for i, p in enumerate(parts)))).alias("x")).select("x.*", "fp")
    probe = nodes.select("fp", F.explode(_flip(parts)).alias("x")).select("x.*", F.col("fp").alias("probe"))
    full = held.groupBy("part", "key").agg(F.count(F.lit(1)).alias("n"))
    sized = held.join(full.where("n > 1") if all(p.radius == 0 for p in parts) else full, ["part", "key"])
    near = F.bit_count(F.col("fp").bitwiseXOR(F.col("probe"))) <= radius
    thin = sized.where(F.col("n") <= dense).join(probe, ["part", "key"]).where(near & (F.col("probe") < F.col("fp")))
    edges = thin.select(F.col("probe").alias("a"), F.col("fp").alias("b"))
    if radius != 2:
        thick = sized.where(F.col("n") > dense).join(probe, ["part", "key"]).where(near & (F.col("probe") < F.col("fp")))
        return edges.unionByName(thick.select(F.col("probe").alias("a"), F.col("fp").alias("b")))
    crowded = full.where(F.col("n") > dense).select("part", "key")
    crowd = probe.join(crowded, ["part", "key"], "left_semi").select(F.col("probe").alias("fp")).distinct()
    ball = F.array(F.col("fp"), *(F.col("fp").bitwiseXOR(F.lit(signed(1 << i))) for i in range(BITS)))
    points = crowd.select("fp", F.explode(ball).alias("point")).groupBy("point").agg(F.min("fp").alias("a"), F.collect_set("fp").alias("all"))
    spokes = points.where(F.size("all") > 1).select("a", F.explode("all").alias("b")).where("a < b").distinct()
    return edges.unionByName(spokes)


def near_duplicates(docs: DataFrame, radius: int = RADIUS, dense: int = DENSE) -> DataFrame:
    """Every row with its fingerprint and the least doc_id that links reach from it."""
    prints = cut(fingerprints(docs))
    nodes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = components(links(nodes, radius, dense))
    rooted = nodes.join(roots, nodes["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = rooted.join(least, "root").select("fp", "component_id")
    return prints.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
