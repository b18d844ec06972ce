"""Near copies by SimHash candidates and verified shingle similarity: the pipeline's near-dedup.

Two texts are near copies if the Jaccard similarity of their sets of 5-word
shingles is ``SIMILAR`` or more; every link is checked on the whole sets.

1. Slices of the corpus ask buckets of shingle hashes which of their shingles
   another document has (``sharing``; a shingle is asked once a slice, in four bytes or less).
   A text of which fewer than ``SIMILAR`` of its shingles are shared has no near copy
   and is done. The others keep their sets, and equal sets are one node from here.
2. Fingerprints are over the distinct words of a text. The pigeonhole search of
   ``simhash_dedup`` (same partitions, thresholds and probes, within bins of the sets'
   sizes) proposes each prober with the first member of its bucket (``proposed``).
3. What SimHash cannot see (appended or exchanged blocks) meets by prefixes: of two
   sets of the similarity, each has one of the other's shingles among its first
   ``n - ceil(SIMILAR * n) + 1`` in an order that all sets share, rare ones first. Rows
   of one such shingle (a spot) are compared with the first of them.
4. Spots that still hold several groups are settled in tasks that hold the sets
   (``_settled``): only links that hold exactly join groups there, so nothing hides
   behind an estimate, and at most one link a row comes out. Nodes that such spots
   connect go to one task if their sets have ``WEIGHT`` shingles or fewer in all; else
   each spot is dealt into chunks of that size, and each two chunks meet in one task.

Rows that are emitted grow with the rows that share a key, never with their pairs.

Defined cases: fewer words than a shingle: the whole sequence is one; no words: alike
only to each other; null text counts as empty; rows that repeat a doc_id stay or go
together; a null doc_id stays; extra columns pass through; an empty table stays empty.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapesig.llm.common import cut, few_ids, in_arrow, rows_of, text_bytes
from shapesig.llm.graph import components
from shapesig.llm.kernels import Words, ragged, xxh64_spans
from shapesig.llm.simhash_dedup import Part, bit_counts, plan, signed

RADIUS, SHINGLE, SIMILAR = 4, 5, 0.8
HASH_BITS = 48  # of a shingle's hash; two sets of a thousand share one by chance once in 10^8
WEIGHT = 1_000_000  # shingles whose sets a task compares at once: 8 MB
#: A factor of sizes that two sets of the similarity cannot exceed, as a logarithm.
BIN = math.log(1 / SIMILAR) + 1e-6


def shingles_of(w: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all word runs, and their documents."""
    each = np.where(w.per_doc >= size, w.per_doc - size + 1, (w.per_doc > 0).astype(np.int64))
    doc = np.repeat(np.arange(w.n_docs), each)
    begin = np.cumsum(each) - each
    first = w.first[:-1][doc] + np.arange(len(doc)) - begin[doc]
    last = np.minimum(first + size, w.first[1:][doc]) - 1
    if not len(doc):
        return np.zeros(0, np.uint64), doc
    return xxh64_spans(w.buf, w.start[first], (w.start[last] + w.size[last] - w.start[first]).astype(np.int64)), doc


def distinct(h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct hashes of each document, in order."""
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    return h[new], doc[new]


def sets_of(texts: pa.Array, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Fingerprints of the distinct words, sizes of the sets of shingles, and the sets one after another."""
    w = Words(texts, lower=True)
    h, doc = distinct(w.hashes(), w.doc)
    fp = np.zeros(w.n_docs, np.uint64)
    if len(h):
        at = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
        n = np.diff(np.append(at, len(doc)))
        ones = np.add.reduceat(np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), at, axis=0, dtype=np.int64)
        fp[doc[at]] = np.packbits(ones * 2 > n[:, None], axis=1, bitorder="little").view("<u8").reshape(-1)
    s, of = shingles_of(w, shingle)
    s, of = distinct(s >> np.uint64(64 - HASH_BITS), of)
    return fp, np.bincount(of, minlength=w.n_docs), s


# ---- which shingles another document has

SLICE = "slice long, ids binary, fps binary, sizes binary, h binary"
ASKED = "bucket long, slice long, low binary, times binary"
ANSWER = "slice long, bucket long, bits binary, level binary"
KEPT = "doc_id long, fp long, n long, s array<long>, spots array<long>"
_SLICE, _ASKED, _ANSWER = (pa.schema([(f.split()[0], {"long": pa.int64(), "binary": pa.binary()}[f.split()[1]]) for f in d.split(", ")]) for d in (SLICE, ASKED, ANSWER))
_KEPT = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64()), ("n", pa.int64()), ("s", pa.list_(pa.int64())), ("spots", pa.list_(pa.int64()))])


def slices(docs: DataFrame, size: int, shingle: int = SHINGLE) -> DataFrame:
    """Rows of ``size`` bytes of text or a document more: ids, fingerprints and sets, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        serial = TaskContext.get().partitionId() << 32
        held: list[tuple] = []
        full = 0
        for batch in batches:
            for part in rows_of(batch, "text", 1 << 20):
                held.append((np.asarray(part.column(0)).astype(np.int64), *sets_of(part.column(1), shingle)))
                full += part.column(1).nbytes
                if full >= size:
                    yield _slice(serial, held)
                    held, full, serial = [], 0, serial + 1
        if held:
            yield _slice(serial, held)

    return in_arrow(docs.select("doc_id", "text"), run, SLICE)


def packed(values: np.ndarray, width: int) -> bytes:
    """Steps between whole numbers of ``width`` bytes, bytes of equal rank together: of sorted numbers the high ones are mostly zero and compress away."""
    steps = np.diff(values.astype(np.uint64), prepend=np.uint64(0))
    return np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def unpacked(blob: bytes, width: int) -> np.ndarray:
    steps = np.zeros((len(blob) // width, 8), np.uint8)
    steps[:, :width] = np.frombuffer(blob, np.uint8).reshape(width, -1).T
    with np.errstate(over="ignore"):
        return np.cumsum(steps.view(np.uint64).reshape(-1), dtype=np.uint64) & np.uint64((1 << 8 * width) - 1)


def _slice(serial: int, parts: list[tuple]) -> pa.RecordBatch:
    *about, h = (np.concatenate(c) for c in zip(*parts, strict=True))
    columns = [*(c.tobytes() for c in about), packed(h, HASH_BITS // 8)]
    return pa.RecordBatch.from_arrays([pa.array([serial], pa.int64()), *(pa.array([c], pa.binary()) for c in columns)], schema=_SLICE)


def _asked(h: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of the distinct hashes, in order: the bucket, 32 bits of the place in it, and how often each occurs; and the place of every hash among them."""
    u, place, times = np.unique(h, return_inverse=True, return_counts=True)
    scaled = (u >> np.uint64(8)) * np.uint64(buckets)  # 40 bits times 19 at most
    return (scaled >> np.uint64(40)).astype(np.int64), (scaled >> np.uint64(8)).astype(np.uint32), times, place


def _edges(bucket: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1], [True]])) if len(bucket) else np.zeros(1, np.int64)


def _rows(columns: list, schema: pa.Schema) -> pa.Table:
    return pa.table([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def prefix(n: np.ndarray, doc: np.ndarray, h: np.ndarray, shared: np.ndarray, level: np.ndarray, similar: float) -> tuple[np.ndarray, np.ndarray]:
    """Whether each document can have a near copy, and which hashes stand in its prefix and are shared.

    The order is: hashes of one document, then the others by their level, then the
    hash; a document's first ``n - ceil(similar * n) + 1`` are its prefix.
    """
    many = np.bincount(doc, shared, len(n)).astype(np.int64)
    need = np.ceil(similar * n - 1e-9).astype(np.int64)
    able = many >= need
    order = np.lexsort((h, level, ~shared, doc))  # shared ones come first in each document here
    rank = np.empty(len(h), np.int64)
    rank[order] = np.arange(len(h)) - (np.cumsum(n) - n)[doc[order]]
    return able, shared & able[doc] & (rank <= (many - need)[doc])


def sharing(docs: DataFrame, slice_bytes: int | None = None, buckets: int | None = None, similar: float = SIMILAR) -> DataFrame:
    """(doc_id, fp, n, s, spots) of the documents that can have a near copy: their sets, and the shared shingles of their prefixes.

    Slices grow with the root of the corpus to 32 MB; buckets are those of 16 MB of
    text and 500,000 at most, 200 MB of text at 100 TB. Two hashes of a bucket with
    equal low bits count as one: a text may be kept that need not be, none is lost.
    """
    total = text_bytes(docs) if slice_bytes is None or buckets is None else 0
    size = slice_bytes or min(32 << 20, max(1 << 20, 256 * math.isqrt(total)))
    n_buckets = buckets or max(8, min(500_000, total >> 24))
    cut_up = slices(docs, size)

    def ask(rows: pa.Table) -> pa.Table:
        out: list[tuple] = []
        for serial, blob in zip(rows["slice"].to_pylist(), rows["h"].to_pylist(), strict=True):
            bucket, low, times, _ = _asked(unpacked(blob, HASH_BITS // 8), n_buckets)
            few, at = np.minimum(times, 255).astype(np.uint8), _edges(bucket)
            out += [(int(bucket[a]), serial, packed(low[a:b], 4), few[a:b].tobytes()) for a, b in zip(at[:-1], at[1:], strict=True)]
        return _rows(list(zip(*out, strict=True)) or [[]] * 4, _ASKED)

    def answer(rows: pa.Table) -> pa.Table:
        low = [unpacked(x, 4) for x in rows["low"].to_pylist()]
        times = np.concatenate([np.frombuffer(x, np.uint8) for x in rows["times"].to_pylist()])
        _, place = np.unique(np.concatenate(low), return_inverse=True)
        held = np.bincount(place, times)
        level = np.minimum(255, 8 * np.log2(held)).astype(np.uint8)[place]
        shared = (held > 1)[place]
        ends = np.cumsum([len(x) for x in low])[:-1]
        told = [(np.packbits(s).tobytes(), v[s].tobytes()) for s, v in zip(np.split(shared, ends), np.split(level, ends), strict=True)]
        return _rows([rows["slice"].to_pylist(), rows["bucket"].to_pylist(), *zip(*told, strict=True)], _ANSWER)

    def settle(rows: pa.Table, replies: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return _KEPT.empty_table()
        ids, fps, n = (np.frombuffer(rows[c][0].as_py(), np.int64) for c in ("ids", "fps", "sizes"))
        h = unpacked(rows["h"][0].as_py(), HASH_BITS // 8)
        bucket, _, _, place = _asked(h, n_buckets)
        said = {b: (x, v) for b, x, v in zip(*(replies[c].to_pylist() for c in ("bucket", "bits", "level")), strict=True)}
        at, shared, level = _edges(bucket), np.zeros(len(bucket), bool), np.zeros(len(bucket), np.uint8)
        for a, b in zip(at[:-1], at[1:], strict=True):
            bits, levels = said[int(bucket[a])]
            shared[a:b] = np.unpackbits(np.frombuffer(bits, np.uint8), count=b - a).astype(bool)
            level[a:b][shared[a:b]] = np.frombuffer(levels, np.uint8)
        doc = np.repeat(np.arange(len(n)), n)
        able, chosen = prefix(n, doc, h, shared[place], level[place], similar)
        keep = able[doc]

        def lists(mask: np.ndarray) -> pa.Array:
            ends = np.cumsum(np.concatenate([[0], np.bincount(doc[mask], minlength=len(n))[able]]))
            return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(h[mask].view(np.int64)))

        return pa.table([pa.array(ids[able]), pa.array(fps[able]), pa.array(n[able]), lists(keep), lists(chosen)], schema=_KEPT)

    answers = cut_up.groupBy("slice").applyInArrow(ask, ASKED).groupBy("bucket").applyInArrow(answer, ANSWER)
    return cut_up.groupBy("slice").cogroup(answers.groupBy("slice")).applyInArrow(settle, KEPT)


# ---- candidates and their check


def proposed(nodes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Pairs (a, b) of ``nodes`` (node, fp, n) within the radius: each prober with the first member of its bucket."""
    placed = nodes.where("n > 0").select("node", "fp", "n", F.floor(F.log("n") / BIN).cast("int").alias("bin"))
    n, both = bit_counts(placed)
    sizes = {r["bin"]: r["n"] for r in placed.groupBy("bin").agg(F.count(F.lit(1)).alias("n")).collect()}  # a bin a factor of 1.25
    share = sum(c * (c + sizes.get(b + 1, 0)) for b, c in sizes.items()) / max(1, n) ** 2
    parts = plan(n, both, radius, share=share, copies=2) or [Part(tuple(range(64)), 0)]

    def keys(flips: bool) -> Column:
        return F.explode(F.array(*(F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(F.lit(signed(p.mask))).bitwiseXOR(F.lit(signed(x))).alias("key")) for i, p in enumerate(parts) for x in (p.flips if flips else [0])))).alias("x")

    first = placed.select("*", keys(False)).groupBy("x.part", "x.key", "bin").agg(F.min(F.struct("node", "fp", "n")).alias("p"))
    probe = placed.select("*", keys(True)).select("x.part", "x.key", F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"), "node", "fp", "n")
    met = probe.join(first, ["part", "key", "bin"]).where(F.bit_count(F.col("fp").bitwiseXOR(F.col("p.fp"))) <= radius)
    return _ordered(met.where(_sized(F.col("n"), F.col("p.n"))).select(F.col("node").alias("x"), F.col("p.node").alias("y")))


def _sized(x: Column, y: Column, similar: float = SIMILAR) -> Column:
    return F.least(x, y) >= similar * F.greatest(x, y)


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def verified(pairs: DataFrame, sets: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """Pairs (a, b) of nodes whose sets (node, s) have the similarity."""
    met = pairs.join(sets.select(F.col("node").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("node").alias("b"), F.col("s").alias("sb")), "b")
    both = F.size(F.array_intersect("sa", "sb"))
    return met.where(both >= similar * (F.size("sa") + F.size("sb") - both)).select("a", "b").distinct()


def _settled(root: np.ndarray, sets: list[np.ndarray], similar: float) -> tuple[list[int], list[int]]:
    """Links (places of rows) that join all groups whose sets have the similarity."""
    g = len(sets)
    n = np.array([len(x) for x in sets], np.int64)
    own = np.repeat(np.arange(g), n)
    _, word = np.unique(np.concatenate(sets), return_inverse=True)
    begin = np.cumsum(n) - n
    posts = own[np.argsort(word, kind="stable")]
    times = np.bincount(word)
    start = np.cumsum(times) - times
    group = np.unique(root, return_inverse=True)[1]
    a, b = [], []
    # Members of small groups go first: a large group then isn't compared with itself.
    for i in np.lexsort((np.arange(g), np.bincount(group)[group])).tolist():
        if (group == group[i]).all():
            continue
        mine = word[begin[i] : begin[i] + n[i]]
        both = np.bincount(posts[ragged(start[mine], times[mine])], minlength=g)
        for j in np.flatnonzero((both >= similar * (n + n[i] - both)) & (group != group[i])).tolist():
            if group[j] != group[i]:
                a.append(i)
                b.append(j)
                group[group == group[j]] = group[i]
    return a, b


def joined(spots: DataFrame, sets: DataFrame, links: DataFrame, tried: DataFrame, weight: int = WEIGHT, similar: float = SIMILAR) -> DataFrame:
    """The links (a, b; exact ones) and more, which connect all nodes of the similarity that share a spot.

    ``spots`` has (spot, node, n), ``sets`` (node, s) and ``tried`` the pairs that are checked already.
    """
    # Spots with the same rows are one.
    about = spots.groupBy("spot").agg(F.count(F.lit(1)).alias("rows"), F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("sum"), F.min(F.struct("node", "n")).alias("p"))
    kept = about.where("rows > 1").groupBy("rows", "sum", "p").agg(F.min("spot").alias("spot")).select("spot", "p")
    live = cut(spots.join(kept, "spot"))
    pairs = _ordered(live.where(_sized(F.col("n"), F.col("p.n"), similar)).select(F.col("node").alias("x"), F.col("p.node").alias("y")))
    links = cut(links.unionByName(verified(pairs.join(tried, ["a", "b"], "left_anti"), sets, similar)))
    named = live.join(components(links), "node", "left").select("spot", "node", "n", F.coalesce("root", "node").alias("root"))
    open_ = named.groupBy("spot").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x < y").select("spot")
    rest = cut(named.join(open_, "spot", "left_semi"))
    if rest.isEmpty():
        return links
    hub = rest.groupBy("spot").agg(F.min("node").alias("a"))
    cluster = components(rest.join(hub, "spot").select("a", F.col("node").alias("b"))).select("node", F.col("root").alias("cluster"))
    whose = rest.select("node", "root", "n").distinct().join(cluster, "node")
    heavy = whose.groupBy("cluster").agg(F.sum("n").alias("w")).where(F.col("w") > weight).select("cluster")
    whole = whose.join(heavy, "cluster", "left_anti").select(F.lit(0).alias("kind"), F.col("cluster").alias("spot"), F.lit(0).alias("i"), F.lit(0).alias("j"), "node", "root")
    large = rest.join(cluster.join(heavy, "cluster").select("node"), "node")
    chunks = large.groupBy("spot").agg(F.ceil(2 * F.sum("n") / weight).cast("int").alias("chunks"))
    dealt = large.join(chunks, "spot").withColumn("mine", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    parts = dealt.select(F.lit(1).alias("kind"), "spot", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "node", "root").distinct()

    def sweep(rows: pa.Table) -> pa.Table:
        node, root = (np.asarray(rows[c].combine_chunks()) for c in ("node", "root"))
        order = np.lexsort((node, root))
        s = rows["s"].to_pandas().to_list()
        a, b = (node[order[np.array(x, np.int64)]] for x in _settled(root[order], [s[k] for k in order.tolist()], similar))
        return pa.table({"a": np.minimum(a, b), "b": np.maximum(a, b)})

    more = whole.unionByName(parts).join(sets, "node").groupBy("kind", "spot", "i", "j").applyInArrow(sweep, "a long, b long")
    return cut(links.unionByName(more).distinct())


def groups(docs: DataFrame, radius: int = RADIUS, slice_bytes: int | None = None, buckets: int | None = None, weight: int = WEIGHT) -> DataFrame:
    """(doc_id, least) for every document that isn't alone: the least doc_id of its group."""
    rows = cut(sharing(docs.where("doc_id IS NOT NULL"), slice_bytes, buckets).withColumn("h", F.xxhash64("s")))
    one = cut(rows.groupBy("h", "n").agg(F.min("doc_id").alias("node"), F.min("fp").alias("fp"), F.first("s").alias("s"), F.first("spots").alias("spots")))
    same = rows.join(one.select("h", "n", "node"), ["h", "n"]).where("node < doc_id").select(F.col("node").alias("a"), F.col("doc_id").alias("b"))
    sets = one.select("node", "s")
    pairs = cut(proposed(one.select("node", "fp", "n"), radius))
    links = verified(pairs, sets).unionByName(same)
    spots = one.select(F.explode("spots").alias("spot"), "node", "n")
    return components(joined(spots, sets, links, pairs, weight)).select(F.col("node").alias("doc_id"), F.col("root").alias("least"))


def keep_one(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The documents without those that are near copies of one with a smaller doc_id."""
    gone = groups(docs, radius).groupBy("doc_id").agg(F.min("least").alias("least")).where("least < doc_id").select("doc_id")
    return docs.join(few_ids(cut(gone)), "doc_id", "left_anti").select(docs.columns)
