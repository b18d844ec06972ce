"""Quality classifier: regularised quadratic discriminant analysis of document statistics.

``statistics`` turns each text into 24 numbers (byte classes, word shapes,
repetition), transformed to be near normal. ``fit`` takes, from all training
rows, each class's count, sums and cross products (summed per task, so that the
fit sees 2 small rows a task), shrinks each covariance towards the pooled one and
that one towards its diagonal, and keeps the inverses of the Cholesky factors. A score
is the logistic of the difference of the two log densities (half log determinants and
squared Mahalanobis lengths) plus the log prior odds.

Rows with a crc32(doc_id as text) divisible by 5 are held out and never train.
Labels, lang, source and doc_id are not inputs of a score.

Defined cases: null text counts as empty, and every text has a score; a row whose
doc_id repeats is scored each time; a null doc_id is not held out and has no
label; several labels of one doc_id count as several training rows, a null label
as none; without labels of both classes the prior is used and all scores are 0.5;
extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapesig.llm.common import cut, in_arrow, offsets_of, rows_of
from shapesig.llm.kernels import IS_SPACE, Words, mixed

THRESHOLD, FOLDS = 0.3, 5
MOST_LABELS = 500_000  # labelled documents that a filter learns from: the first of them by a hash of the id
SHRINK, RIDGE = 0.1, 0.02  # towards the pooled covariance, and of that towards its diagonal

# Frequent function words of the corpus languages.
STOP_WORDS = """the of and to in is that it for was on with as by be are this an at from or der die das und in den von zu mit
sich des auf ist im dem nicht ein eine als auch es an werden aus er le la les de des du et un une est en que qui dans pour pas sur au
par el los las y del se por con una su para lo como más""".split()

_CLASS = np.zeros((8, 256), np.float32)
for _i, _set in enumerate((range(97, 123), range(65, 91), range(48, 58), b".,;:'\"-()", b"!?", b"#$%&*|{}<>=~^_+@/\\[]`", b"\n", range(128, 256))):
    _CLASS[_i, list(_set)] = 1
NAMES = ["lower", "upper", "digit", "mark", "bang", "symbol", "newline", "high", "space", "words", "length", "length_sd", "long", "stop", "unique", "top", "pair_unique", "tri_unique", "shout", "odd_end", "bare", "entropy", "neighbour", "end_mark"]
WIDTH = len(NAMES)


def _means(values: np.ndarray, first: np.ndarray, n: np.ndarray) -> np.ndarray:
    sums = np.concatenate([[0.0], np.cumsum(values, dtype=np.float64)])
    return (sums[first[1:]] - sums[first[:-1]]) / np.maximum(n, 1)


def _distinct(keys: np.ndarray, doc: np.ndarray, docs: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys of each document, and the count of its most frequent one."""
    with np.errstate(over="ignore"):
        k = mixed(keys + (doc.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))
    _, at, times = np.unique(k, return_index=True, return_counts=True)
    top = np.zeros(docs, np.int64)
    np.maximum.at(top, doc[at], times)
    return np.bincount(doc[at], minlength=docs), top


def statistics_of(texts: pa.Array) -> np.ndarray:
    """Transformed statistics, one row a text."""
    texts = pc.fill_null(texts, "")
    off = offsets_of(texts)
    raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[off[0] : off[-1]]
    off = off - off[0]
    size = np.diff(off)
    w = Words(texts)
    n, docs, doc, first = w.per_doc, w.n_docs, w.doc, w.first
    logit = lambda x: np.log((x + 0.002) / (1.002 - np.minimum(x, 1.0)))
    cols = [logit(_means(c[raw], off, size)) for c in _CLASS]
    cols.append(logit(_means(IS_SPACE[raw], off, size)))
    cols.append(np.log1p(n))
    wide = w.size.astype(np.float64)
    mean = _means(wide, first, n)
    cols += [np.log1p(mean), np.log1p(np.sqrt(np.maximum(_means(wide**2, first, n) - mean**2, 0))), logit(_means(wide > 14, first, n))]
    h = w.hashes()
    cols.append(logit(_means(np.isin(h, _STOP), first, n)))
    kinds, top = _distinct(h, doc, docs)
    cols += [logit(kinds / np.maximum(n, 1)), logit(top / np.maximum(n, 1))]
    for k in (1, 2):
        m = max(0, len(h) - k)
        inside = doc[k:] == doc[:m]
        with np.errstate(over="ignore"):
            keys = sum((h[j : j + m] * np.uint64(2 * j + 3) for j in range(k + 1)), np.zeros(m, np.uint64))
        d, _ = _distinct(keys[inside], doc[:m][inside], docs)
        cols.append(logit(d / np.maximum(n - k, 1)))
    last, head = w.buf[np.maximum(w.start + w.size - 1, 0)], w.buf[w.start]
    second = w.buf[np.minimum(w.start + 1, len(w.buf) - 1)]
    cols.append(logit(_means((_CLASS[1][head] > 0) & (_CLASS[1][second] > 0) & (w.size > 1), first, n)))
    cols.append(logit(_means((_CLASS[5][last] + _CLASS[4][last]) > 0, first, n)))
    letters = np.concatenate([[0], np.cumsum((_CLASS[0] + _CLASS[1] + _CLASS[7])[w.buf])])
    cols.append(logit(_means(letters[w.start + w.size] == letters[w.start], first, n)))
    hist = np.bincount(np.repeat(np.arange(docs), size) * 256 + raw, minlength=docs * 256).reshape(docs, 256)
    p = hist / np.maximum(size, 1)[:, None]
    cols.append(-(p * np.log2(np.maximum(p, 1e-12))).sum(1))
    same = np.zeros(len(h), bool)
    same[1:] = (h[1:] == h[:-1]) & (doc[1:] == doc[:-1])
    cols += [logit(_means(same, first, n)), logit(_means(_CLASS[3][last] > 0, first, n))]
    return np.stack(cols, 1)


_STOP = Words(pa.array(sorted(set(STOP_WORDS)))).hashes()


def statistics(docs: DataFrame) -> DataFrame:
    """(doc_id, x) for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in rows_of(batch, "text", 1 << 19):
                x = statistics_of(part.column(1)).astype(np.float32)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.FixedSizeListArray.from_arrays(pa.array(x.reshape(-1)), WIDTH).cast(pa.list_(pa.float32()))], ["doc_id", "x"])

    return in_arrow(docs.select("doc_id", "text"), run, "doc_id long, x array<float>")


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % FOLDS == 0, F.lit(False))


@dataclass(frozen=True)
class Model:
    """Means, inverted Cholesky factors and log determinants of the two classes, and the log prior odds of class 1."""

    mean: np.ndarray
    inverse: np.ndarray
    log_det: np.ndarray
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        density = [-0.5 * (((x - self.mean[k]) @ self.inverse[k].T) ** 2).sum(1) - 0.5 * self.log_det[k] for k in (0, 1)]
        return 1 / (1 + np.exp(-np.clip(density[1] - density[0] + self.prior, -500, 500)))


def _inverted(factor: np.ndarray) -> np.ndarray:
    """The inverse of a lower triangular matrix, by forward substitution."""
    out = np.zeros_like(factor)
    for i in range(len(factor)):
        out[i] = -factor[i, :i] @ out[:i]
        out[i, i] += 1
        out[i] /= factor[i, i]
    return out


def fit(rows: DataFrame, shrink: float = SHRINK, ridge: float = RIDGE) -> Model | None:
    """The model of ``rows`` (x, label 0 or 1), all of which count; None if a class has no row."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, 1 + WIDTH + WIDTH * WIDTH))
        for batch in batches:
            x = np.asarray(batch.column(0).flatten(), np.float64).reshape(-1, WIDTH)
            y = np.asarray(batch.column(1))
            for k in (0, 1):
                z = x[y == k]
                total[k] += np.concatenate([[len(z)], z.sum(0), (z.T @ z).reshape(-1)])
        yield pa.RecordBatch.from_arrays([pa.array([0, 1], pa.int32()), pa.array(total.tolist())], ["label", "s"])

    width = 1 + WIDTH + WIDTH * WIDTH
    parts = rows.select("x", F.col("label").cast("int").alias("label")).where("label IN (0, 1)").mapInArrow(sums, "label int, s array<double>")
    got = parts.select("label", F.posexplode("s").alias("i", "v")).groupBy("label", "i").agg(F.sum("v").alias("v")).collect()
    total = np.zeros((2, width))
    for r in got:
        total[r["label"], r["i"]] = r["v"]
    n = total[:, 0]
    if n.min() < 2:
        return None
    mean = total[:, 1 : 1 + WIDTH] / n[:, None]
    cov = [total[k, 1 + WIDTH :].reshape(WIDTH, WIDTH) / n[k] - np.outer(mean[k], mean[k]) for k in (0, 1)]
    pooled = (n[0] * cov[0] + n[1] * cov[1]) / n.sum()
    scale = np.diag(np.diag(pooled) + 1e-4)
    pooled = (1 - ridge) * pooled + ridge * scale
    final = [(1 - shrink) * ((1 - ridge) * c + ridge * scale) + shrink * pooled for c in cov]
    factor = np.stack([np.linalg.cholesky(c) for c in final])
    return Model(mean, np.stack([_inverted(f) for f in factor]), np.array([2 * np.log(np.diag(f)).sum() for f in factor]), float(np.log(n[1] / n[0])))


def score(docs: DataFrame, labels: DataFrame, label: str = "quality", threshold: float = THRESHOLD) -> DataFrame:
    """Every row's score and decision by a model fitted on the labelled rows that are not held out."""
    stats = cut(statistics(docs).withColumn("held_out", held_out()))
    # Labels meet the numbers, not the texts.
    known = labels.select(F.col("doc_id").alias("l_"), F.col(label).alias("label"))
    model = fit(stats.where(~F.col("held_out")).join(known, F.col("doc_id") == F.col("l_")).select("x", "label"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.asarray(batch.column(1).flatten(), np.float64).reshape(-1, WIDTH)
            s = model.score(x) if model else np.full(len(x), 0.5)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(s), pa.array((s >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return stats.select("doc_id", "x", "held_out").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def accepted(docs: DataFrame, labels: DataFrame, label: str = "quality", threshold: float = THRESHOLD, most: int = MOST_LABELS) -> DataFrame:
    """The rows (all columns) that score ``threshold`` or more; texts are scored where they are read, not joined."""
    # The fit reads a bounded number of labelled documents, so that only their texts are read twice.
    known = labels.select(F.col("doc_id").alias("l_"), F.col(label).alias("label")).where("label IN (0, 1)")
    chosen = known.select("l_").distinct().orderBy(F.xxhash64("l_"), "l_").limit(most)
    learned = docs.select("doc_id", "text").where(~held_out()).join(F.broadcast(chosen), F.col("doc_id") == F.col("l_"), "left_semi")
    model = fit(statistics(learned).join(known, F.col("doc_id") == F.col("l_")).select("x", "label"))
    if model is None:
        return docs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in rows_of(batch, "text", 1 << 19):
                s = model.score(statistics_of(part.column(part.schema.get_field_index("text"))))
                yield part.filter(pa.array(s >= threshold))

    return in_arrow(docs, run, docs.schema)
