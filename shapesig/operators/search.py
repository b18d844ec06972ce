"""Nearest shapes by area Jaccard distance: exact, through buckets, by range, and self-joins.

Queries are a stated set against all shapes. Their rings go to the workers once
(a broadcast behind ``MOST_QUERY_BYTES``; beyond it the queries are dealt in
blocks and each block makes a pass). A task looks its own shapes up in the queries'
codes, spares those whose shares of a grid's cells show that they are too far, and
keeps the k best for each query: what is shuffled is k rows per query and task.
Queries of one ring are met once, and share what is found.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shapesig.functions.kernels import COARSE, Celled, Grid, Rings, blocks_of, distances, first_hits_of, spans, upper_bound
from shapesig.operators import index as ix
from shapesig.operators.prepare import Frame
from shapesig.operators.signature import _flat, signature, slots_of

MOST_QUERY_BYTES = 256 << 20
#: Numbers of a block of shapes in a task: cells times shapes. Each query's steps through a block cost alike for few shapes and many.
MOST_CELLS = 1 << 23


class Asked:
    """A block of the query set: ids in order, rings in flat arrays."""

    def __init__(self, t: pa.Table):
        t = t.sort_by("pid").combine_chunks()
        ring = t["ring"].combine_chunks() if t.num_rows else pa.array([], t.schema.field("ring").type)
        self.ids = np.asarray(t["pid"]).astype(np.int64)
        self.x, self.y, self.size = _flat(ring)

    def __len__(self) -> int:
        return len(self.ids)

    def rings(self) -> Rings:
        return Rings(self.x, self.y, np.concatenate([[0], np.cumsum(self.size)]).astype(np.int64))

    def once(self) -> Once:
        return Once(self)


class Once(Asked):
    """Each ring of a block once, under its least id; ``members`` are the ids that have it, ``many`` of them ring by ring."""

    def __init__(self, block: Asked):
        ends = np.cumsum(block.size)
        seen: dict[bytes, list[int]] = {}
        for i, (a, b) in enumerate(zip((ends - block.size).tolist(), ends.tolist(), strict=True)):
            seen.setdefault(hashlib.sha256(block.x[a:b].tobytes() + block.y[a:b].tobytes()).digest(), []).append(i)
        first = np.array([at[0] for at in seen.values()], np.int64)
        keep = spans((ends - block.size)[first], block.size[first])
        self.ids, self.x, self.y, self.size = block.ids[first], block.x[keep], block.y[keep], block.size[first]
        self.members = block.ids[np.array([i for at in seen.values() for i in at], np.int64)]
        self.many = np.array([len(at) for at in seen.values()], np.int64)


def query_blocks(q: DataFrame, most: int = MOST_QUERY_BYTES) -> list[Asked]:
    """The query set in blocks of bounded size."""
    r = q.agg(F.count(F.lit(1)).alias("n"), F.sum(F.size("ring") * 16 + 64).alias("b")).first()
    blocks = max(1, -(-(r["b"] or 0) // most))
    out = []
    for i in range(blocks):
        part = q.where(F.pmod(F.xxhash64("pid"), F.lit(blocks)) == i) if blocks > 1 else q
        out.append(Asked(part.select("pid", "ring").toArrow()))
    return out


def top_k(found: DataFrame, k: int) -> DataFrame:
    """(qid, rank, pid, jd) of the k nearest; ties by pid."""
    w = Window.partitionBy("qid").orderBy("jd", "pid")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rank", "pid", "jd")


_FOUND = "qid long, pid long, jd double"


def _rings(batch: pa.RecordBatch) -> Rings:
    ring = batch.column(1)
    flat = ring.flatten()
    return Rings(np.asarray(flat.field(0)).astype(np.int64), np.asarray(flat.field(1)).astype(np.int64), np.asarray(ring.offsets).astype(np.int64) - ring.offsets[0].as_py())


def gathered(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of ``rows``, but for the last."""
    held, n = [], 0
    for batch in batches:
        while batch.num_rows:
            part, batch = batch.slice(0, rows - n), batch.slice(rows - n)
            held.append(part)
            n += part.num_rows
            if n == rows:
                yield _joined(held)
                held, n = [], 0
    if n:
        yield _joined(held)


def _joined(batches: list[pa.RecordBatch]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.concat_arrays([b.column(i) for b in batches]) for i in range(batches[0].num_columns)], batches[0].schema.names)


class Best:
    """The k nearest of each query so far, by distance and id (``more`` of some); with ``ties`` all as near as the k-th; without k all within ``most``."""

    def __init__(self, n: int, k: int | None, most: float | None = None, ties: bool = False, more: np.ndarray | None = None):
        self.k, self.most, self.ties, self.more = k, np.inf if most is None else most, ties, np.zeros(n, np.int64) if more is None else more
        self.found = [(np.zeros(0), np.zeros(0, np.int64))] * n

    def wanted(self, j: int) -> int | None:
        return None if self.k is None else self.k + int(self.more[j])

    def limit(self, j: int) -> float:
        d, k = self.found[j][0], self.wanted(j)
        return min(self.most, d[k - 1]) if k is not None and len(d) >= k else self.most

    def add(self, j: int, d: np.ndarray, pid: np.ndarray) -> None:
        keep = d <= self.limit(j)
        if keep.any():
            d, pid = np.concatenate([self.found[j][0], d[keep]]), np.concatenate([self.found[j][1], pid[keep]])
            order, k = np.lexsort((pid, d)), self.wanted(j)
            if k is not None and len(d) > k:
                order = order[: int(np.searchsorted(d[order], d[order][k - 1], "right")) if self.ties else k]
            self.found[j] = d[order], pid[order]


class Codes:
    """Where each query's codes stand among a block's shapes, for bands of several lengths: a lookup by sorted codes."""

    def __init__(self, shapes: np.ndarray, queries: np.ndarray, lengths: tuple[int, ...], bands: int):
        wide = max(lengths)
        self.n, self.at = len(shapes), {m: [] for m in lengths}
        for b in range(bands):
            both = np.concatenate([shapes[:, b * wide : (b + 1) * wide], queries[:, b * wide : (b + 1) * wide]])
            code, shut = np.zeros(len(both), np.int64), np.zeros(len(both), bool)
            for m in range(1, wide + 1):
                code = np.unique(code << 32 | both[:, m - 1], return_inverse=True)[1].astype(np.int64)
                shut |= both[:, m - 1] == 0  # an open slot leaves its band out
                if m in self.at:
                    mine, theirs = np.where(shut, -1, code)[: self.n], np.where(shut, -2, code)[self.n :]
                    order = np.argsort(mine, kind="stable")
                    self.at[m].append((order, np.searchsorted(mine[order], theirs), np.searchsorted(mine[order], theirs, "right")))
        self.lo, self.hi = ({m: np.stack([a[i] for a in at]) for m, at in self.at.items()} for i in (1, 2))

    def of(self, m: int, j: int) -> np.ndarray:
        """The shapes that share a bucket of length ``m`` with query ``j``."""
        lo, hi = self.lo[m][:, j], self.hi[m][:, j]
        met = np.zeros(self.n, bool)
        for b in np.flatnonzero(hi > lo):
            met[self.at[m][b][0][lo[b] : hi[b]]] = True
        return np.flatnonzero(met)


_LISTS = "m int, qid long, pid long, jd double, cands long"


def nearest(poly: DataFrame, q: DataFrame, k: int | None, exact: bool = True, frame: Frame | None = None, lengths: tuple[int, ...] = (), bands: int = 2, cap: int | None = None, base_seed: int = 42, exclude_self: bool = True, most: float | None = None, ties: bool = False) -> DataFrame:
    """(m, qid, pid, jd, cands): each task's nearest of all shapes (m 0), and of those that share a bucket of a length ``m``.

    One pass over the shapes serves all of them; a row without ``qid`` has the
    candidates that a task met at a length. No pair of a candidate leaves a task
    unless it is among the task's best. A ring that several queries have is met
    once, and one shape more is kept for it, as each of them leaves itself out.
    """
    kinds = (*([0] if exact else []), *lengths)
    wanted = tuple(slots_of(max(lengths), bands)) if lengths else ()
    key = frame.key if lengths else ()
    parts, blocks = [], [block.once() for block in query_blocks(q)]
    for block in blocks:

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            fine = 4 if block.size.mean() >= 40 else 2
            grid = Grid(block.x, block.y, fine)
            rings = block.rings()
            asked = Celled(rings, grid)
            ids, many = block.ids[asked.order], block.many[asked.order]
            own = np.split(block.members, np.cumsum(block.many)[:-1])
            own = [own[i] for i in asked.order]
            theirs = first_hits_of(block.x, block.y, block.size, key, wanted, cap, base_seed)[asked.order] if lengths else None
            best = {m: Best(len(ids), k, most, ties, (many > 1).astype(np.int64) * exclude_self) for m in kinds}
            cands = dict.fromkeys(lengths, 0)
            step = MOST_CELLS // (COARSE * fine) ** 2
            for batch in gathered(batches, step):
                shapes = Celled(_rings(batch), grid)
                pids = np.asarray(batch.column(0)).astype(np.int64)[shapes.order]
                codes = Codes(first_hits_of(*_flat(batch.column(1)), key, wanted, cap, base_seed)[shapes.order], theirs, lengths, bands) if lengths else None
                known = np.full(len(pids), np.nan) if len(kinds) > 1 else None
                for j, qid in enumerate(ids):
                    but, met = qid if exclude_self and many[j] == 1 else None, []
                    for m in kinds:
                        among = codes.of(m, j) if m else None
                        if m:
                            others = among[pids[among] != but] if but is not None else among
                            cands[m] += many[j] * len(others) - (np.isin(pids[among], own[j]).sum() if exclude_self and but is None else 0)
                            among = others
                        _improve(best[m], shapes, pids, asked, j, among, known, met, but)
                    if met:
                        known[np.concatenate(met)] = np.nan
            for m in kinds:
                for i in range(0, len(ids), 1000):
                    some = [(np.full(len(d), ids[j]), pid, d) for j, (d, pid) in enumerate(best[m].found[i : i + 1000], i) if len(d)]
                    if some:
                        qid, pid, d = (np.concatenate(c) for c in zip(*some, strict=True))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(d), m, np.int32)), pa.array(qid), pa.array(pid), pa.array(d), pa.nulls(len(d), pa.int64())], ["m", "qid", "pid", "jd", "cands"])
            if lengths:
                n = len(lengths)
                yield pa.RecordBatch.from_arrays([pa.array(lengths, pa.int32()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.float64()), pa.array([cands[m] for m in lengths], pa.int64())], ["m", "qid", "pid", "jd", "cands"])

        if len(block):
            # What a task does for its queries before it meets a shape, and the lists that it hands on, are as many as the tasks.
            parts.append(poly.select("pid", "ring").coalesce(poly.sparkSession.sparkContext.defaultParallelism).mapInArrow(run, _LISTS))
    if not parts:
        return poly.sparkSession.createDataFrame([], _LISTS)
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    return found if all((b.many == 1).all() for b in blocks) else _to_members(found, blocks, k, exclude_self, ties)


def _to_members(found: DataFrame, blocks: list[Once], k: int | None, exclude_self: bool, ties: bool) -> DataFrame:
    """What was found for a ring, for each query that has it; only the nearest of all tasks are handed out."""
    if k is not None:
        w = Window.partitionBy("m", "qid").orderBy("jd", *([] if ties else ["pid"]))
        found = found.withColumn("r", F.rank().over(w) if ties else F.row_number().over(w)).where(F.col("qid").isNull() | (F.col("r") <= k + exclude_self)).drop("r")
    ids, many, members = (np.concatenate([getattr(b, f) for b in blocks]) for f in ("ids", "many", "members"))
    order = np.argsort(ids)
    ids, start, many = ids[order], (np.cumsum(many) - many)[order], many[order]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            asked = batch.column(1).is_valid()
            yield batch.filter(pa.array(~np.asarray(asked)))
            some = batch.filter(asked)
            at = np.searchsorted(ids, np.asarray(some.column(1)).astype(np.int64))
            for rows in blocks_of(many[at]):
                n, qid = many[at[rows]], members[spans(start[at[rows]], many[at[rows]])]
                each = some.take(pa.array(np.repeat(np.arange(rows.start, rows.stop), n))).set_column(1, "qid", pa.array(qid))
                yield each.filter(pa.array(qid != np.asarray(each.column(2)))) if exclude_self else each

    return found.mapInArrow(run, _LISTS)


def _improve(best: Best, shapes: Celled, pids: np.ndarray, asked: Celled, j: int, among: np.ndarray | None, known: np.ndarray | None, met: list[np.ndarray], but: int | None) -> None:
    """Query ``j`` meets a block's shapes: the likeliest first, so that their distances spare others. Those ``met`` have a ``known`` distance."""

    def measure(at: np.ndarray) -> None:
        new = at if known is None else at[np.isnan(known[at])]
        d = np.round(distances(shapes.rings.pick(new), asked.rings, j), 6) if len(new) else np.zeros(0)
        if known is not None:
            known[new] = d
            d = known[at]
            met.append(new)
        best.add(j, d, pids[at])

    def likely(among: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        at, alike = shapes.near(asked, j, best.limit(j), among)
        keep = pids[at] != but if but is not None else np.ones(len(at), bool)
        return at[keep], alike[keep]

    done, k = None, best.wanted(j)
    if k is not None and not np.isfinite(best.limit(j)):
        # Nothing to spare by yet: the likeliest of those of like area give a first limit.
        at, alike = likely(shapes.around(asked.area[j], 16 * k + 100, among))
        done = at[np.argsort(-alike, kind="stable")[:k]]
        if len(done):
            measure(done)
    at, alike = likely(among)
    if done is not None:
        keep = ~np.isin(at, done)
        at, alike = at[keep], alike[keep]
    while k is not None and len(at) > 2 * k:
        # Twice as many each time.
        first = np.argpartition(-alike, k)[:k]
        measure(at[first])
        rest = np.ones(len(at), bool)
        rest[first] = False
        rest &= 1 - alike <= best.limit(j) + 1e-6
        fewer = rest.sum() < 0.5 * len(at)
        at, alike = at[rest], alike[rest]
        if not fewer:
            break
    if len(at):
        measure(at)


def knn_exact(poly: DataFrame, q: DataFrame, k: int | None, exclude_self: bool = True, bounds: bool = True, most: float | None = None, ties: bool = False) -> DataFrame:
    """Every query against every shape. Shapes that can't enter the k best are not refined, unless ``bounds`` is False: brute force.

    ``k`` None with ``most`` gives all shapes within that distance; with ``ties`` there is no rank, and all at the k-th distance stay.
    """
    if bounds:
        found = nearest(poly, q, k, exclude_self=exclude_self, most=most, ties=ties).select("qid", "pid", "jd")
    else:
        found = _all(poly, q, k, exclude_self, most)
    return found if k is None or ties else top_k(found, k)


def _all(poly: DataFrame, q: DataFrame, k: int | None, exclude_self: bool, most: float | None) -> DataFrame:
    """Brute force without any bound."""
    parts = []
    for block in query_blocks(q):

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            queries, best = block.rings(), Best(len(block), k, most)
            for batch in batches:
                if not batch.num_rows:
                    continue
                many, pids = _rings(batch), np.asarray(batch.column(0)).astype(np.int64)
                for j, qid in enumerate(block.ids):
                    use = pids != qid if exclude_self else np.ones(len(pids), bool)
                    best.add(j, np.round(distances(many, queries, j), 6)[use], pids[use])
            for qid, (d, at) in zip(block.ids, best.found, strict=True):
                if len(d):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(d), qid, np.int64)), pa.array(at), pa.array(d)], ["qid", "pid", "jd"])

        parts.append(poly.select("pid", "ring").mapInArrow(run, _FOUND))
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    return found


def similarity_tenths(poly: DataFrame, q: DataFrame, frame: Frame, slots: list[int], base_seed: int = 42) -> DataFrame:
    """(tenth, pairs, mean_j, mean_share) over all pairs of a query and another shape: sums leave a task, pairs don't."""
    key, wanted = frame.key, tuple(slots)
    parts = []
    for block in query_blocks(q):

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            queries, theirs = block.rings(), first_hits_of(block.x, block.y, block.size, key, wanted, None, base_seed) if len(block) else None
            sums = np.zeros((3, 10))
            for batch in batches:
                if not batch.num_rows:
                    continue
                many, pids = _rings(batch), np.asarray(batch.column(0)).astype(np.int64)
                mine = first_hits_of(*_flat(batch.column(1)), key, wanted, None, base_seed)
                for j, qid in enumerate(block.ids):
                    alike = 1 - np.round(distances(many, queries, j), 6)
                    share = (mine == theirs[j]).sum(1)
                    tenth = np.minimum(np.floor(np.round(alike * 10, 5)), 9).astype(int)[pids != qid]
                    for row, values in zip(sums, (None, alike, share), strict=True):
                        row += np.bincount(tenth, None if values is None else values[pids != qid], 10)
            some = np.flatnonzero(sums[0])
            yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(sums[0, some].astype(np.int64)), pa.array(sums[1, some]), pa.array(sums[2, some].astype(np.int64))], ["tenth", "n", "j", "equal"])

        parts.append(poly.select("pid", "ring").mapInArrow(run, "tenth int, n long, j double, equal long"))
    sums = parts[0]
    for p in parts[1:]:
        sums = sums.unionByName(p)
    n = F.sum("n")
    return sums.groupBy("tenth").agg(n.alias("pairs"), F.round(F.sum("j") / n, 6).alias("mean_j"), F.round(F.sum("equal") / (n * len(slots)), 6).alias("mean_share"))


#: Candidates of one shape that travel with its ring; a shape that more queries ask for has several rows.
MOST_ASKED = 4096


def refine(cand: DataFrame, poly: DataFrame, q: DataFrame, most: float | None = None) -> DataFrame:
    """Exact distances of candidate pairs (qid, pid): a shape's ring is fetched once for all its queries, whose rings are with the workers."""
    deal = F.pmod(F.xxhash64("qid"), F.greatest(F.lit(1), F.ceil(F.lit(q.count() / MOST_ASKED)).cast("int")))
    # Few bytes, much work: a stated number of partitions isn't coalesced by their size.
    spread = max(q.sparkSession.sparkContext.defaultParallelism, int(q.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    asked = cand.repartition(spread, "pid").groupBy("pid", deal.alias("deal")).agg(F.collect_list("qid").alias("qids"))
    met = asked.join(poly.select("pid", "ring"), "pid").select("pid", "ring", "qids")
    parts = []
    for block in query_blocks(q):

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            ids, queries = block.ids, block.rings()
            for batch in batches:
                if not batch.num_rows or not len(ids):
                    continue
                many, pids, lists = _rings(batch), np.asarray(batch.column(0)).astype(np.int64), batch.column(2)
                qids = np.asarray(lists.flatten()).astype(np.int64)
                at = np.repeat(np.arange(len(pids)), np.diff(np.asarray(lists.offsets)))
                order = np.argsort(qids, kind="stable")
                qids, at = qids[order], at[order]
                edges = np.searchsorted(qids, ids), np.searchsorted(qids, ids, "right")
                out = []
                for j, (a, b) in enumerate(zip(*(e.tolist() for e in edges), strict=True)):
                    if a == b:
                        continue
                    mask = np.zeros(len(pids), bool)
                    mask[at[a:b]] = True
                    d = np.round(distances(many.take(mask), queries, j), 6)
                    keep = d <= most if most is not None else np.ones(len(d), bool)
                    out.append((np.full(int(keep.sum()), ids[j]), pids[mask][keep], d[keep]))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], ["qid", "pid", "jd"])

        parts.append(met.mapInArrow(run, _FOUND))
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    return found


def candidate_pairs(poly: DataFrame, q: DataFrame, frame: Frame, m: int, bands: int = 2, cap: int | None = None, base_seed: int = 42, exclude_self: bool = True) -> DataFrame:
    """The filter step: (qid, pid) that share a bucket."""
    index = ix.bucket_index(signature(poly, frame, m, bands, cap, base_seed), m, bands)
    probes = ix.bucket_index(signature(q, frame, m, bands, cap, base_seed), m, bands)
    return ix.candidates(probes, index, exclude_self)


def knn_approx(poly: DataFrame, q: DataFrame, frame: Frame, k: int, m: int, bands: int = 2, cap: int | None = None, base_seed: int = 42, exclude_self: bool = True) -> DataFrame:
    """Hash, probe and refine: (qid, rank, pid, jd). Candidates stay in the task that has the shape."""
    found = nearest(poly, q, k, False, frame, (m,), bands, cap, base_seed, exclude_self)
    return top_k(found.where("qid IS NOT NULL").select("qid", "pid", "jd"), k)


def nearest_set(found: DataFrame) -> DataFrame:
    """All shapes tied at a query's least distance."""
    w = Window.partitionBy("qid").orderBy("jd")
    return found.withColumn("r", F.rank().over(w)).where("r = 1").drop("r")


def range_search(poly: DataFrame, q: DataFrame, most: float, exclude_self: bool = True) -> DataFrame:
    """All (qid, pid, jd) within ``most``, exact; bounds spare what can't be."""
    return knn_exact(poly, q, None, exclude_self, most=most)


def same_shapes(poly: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct centred shapes under their least pid, and the membership (pid, cls) of all."""
    key = poly.groupBy("ring").agg(F.min("pid").alias("cls"))
    members = poly.join(key, "ring").select("pid", "cls")
    return key.select(F.col("cls").alias("pid"), "ring"), members


def self_join(poly: DataFrame, most: float, frame: Frame | None = None, m: int | None = None, bands: int = 2, cap: int | None = None) -> DataFrame:
    """Pairs (a, b, jd) of distinct shapes within ``most``.

    Without ``m``: exact, by bins of the logarithm of the area (shapes within the
    distance lie in the same or neighbouring bins). With ``m``: pairs that share a
    bucket of the signature index. Bins and buckets are dealt in tiles of bounded
    size, each two tiles of a bin in one task, and only links come out.
    """
    low = 1 - most
    if m is None:
        b = F.floor(F.log(F.col("area2").cast("double")) / float(-np.log(low))).cast("long")
        placed = poly.select("pid", "ring", "area2", b.alias("bin"))
        rows = placed.select("pid", "ring", F.explode(F.array(F.struct(F.col("bin").alias("key"), F.lit(True).alias("own")), F.struct((F.col("bin") + 1).alias("key"), F.lit(False).alias("own")))).alias("s")).select("pid", "ring", "s.*")
    else:
        index = ix.bucket_index(signature(poly, frame, m, bands, cap), m, bands)
        rows = index.join(poly.select("pid", "ring"), "pid").select("pid", "ring", "key", F.lit(True).alias("own"))
    return _tiled(rows, most).distinct()


TILE = 2000


def _tiled(rows: DataFrame, most: float) -> DataFrame:
    """Links among the rows of each key: own with own, and own with guests; tiles bound a task's memory."""
    sizes = rows.groupBy("key").agg(F.ceil(F.count(F.lit(1)) / TILE).cast("int").alias("tiles"))
    dealt = rows.join(sizes, "key").withColumn("t", F.pmod(F.xxhash64("pid"), F.col("tiles")).cast("int"))
    cells = dealt.withColumn("u", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))).select("key", F.least("t", "u").alias("i"), F.greatest("t", "u").alias("j"), "t", "pid", "own", "ring")

    def run(table: pa.Table) -> pa.Table:
        pid, own = (np.asarray(table[c].combine_chunks()) for c in ("pid", "own"))
        t, cross = np.asarray(table["t"].combine_chunks()), table["i"][0].as_py() != table["j"][0].as_py()
        rings = Rings.of(table["ring"].to_pylist())
        out = []
        for k in np.flatnonzero(own):
            use = (pid != pid[k]) & (~own | (pid > pid[k]))
            if cross:
                use &= t != t[k]
            use &= upper_bound(rings, rings, k) >= 1 - most - 1e-6
            if use.any():
                d = np.round(distances(rings.take(use), rings, k), 6)
                at = pid[use][d <= most]
                out.append((np.minimum(at, pid[k]), np.maximum(at, pid[k]), d[d <= most]))
        got = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table([pa.array(got[0].astype(np.int64)), pa.array(got[1].astype(np.int64)), pa.array(got[2].astype(float))], names=["a", "b", "jd"])

    return cells.groupBy("key", "i", "j").applyInArrow(run, "a long, b long, jd double")
