"""Exact dedup by a minimal perfect hash over the digests of an earlier corpus.

``build_index`` turns the distinct digests of the history into shards. A shard
holds a minimal perfect hash (levels of bit arrays; a digest's slot is the rank
of its first unshared bit), and its slots hold the full digest, the locator
(doc_id) of the winner and the number of copies. ``look_up`` sends distinct
incoming digests to their shards, compares all 32 bytes with the slot's digest,
and tells members from nonmembers; nonmembers are grouped among themselves.

Digests are aggregated before any shuffle (a hot text is one row per task), and
a shard is bounded by ``SHARD_ROWS`` distinct digests on average, not by copies.

Defined cases: null text counts as empty; empty texts equal each other; rows
that repeat a doc_id are counted like any other, all with that id; a null doc_id
wins only if no copy has an id; extra columns are ignored; an empty table gives
no rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapesig.llm.common import SPACE, cut
from shapesig.llm.kernels import mixed

SHARD_ROWS = 50_000
LOAD = 2.0  # bits of a level for each digest that is still without a slot


def text_digest(text: Column) -> Column:
    """SHA-256 (lowercase hex) of the text with each run of white space made one space."""
    return F.sha2(F.regexp_replace(F.coalesce(text, F.lit("")), f"{SPACE}+", " "), 256)


def digests(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.unhex(text_digest(F.col("text"))).alias("digest"))


def _words(blob: np.ndarray) -> np.ndarray:
    """Digests (n x 32 bytes) as n x 4 unsigned words."""
    return np.ascontiguousarray(blob).view("<u8").reshape(-1, 4)


def _place(words: np.ndarray, level: int, size: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mixed(words[:, level & 3] + np.uint64(level) * np.uint64(0x9E3779B97F4A7C15) + words[:, (level + 1) & 3]) % np.uint64(size)


def build_levels(words: np.ndarray) -> list[np.ndarray]:
    """Bit arrays of the levels; every digest has exactly one set bit of its own in one of them."""
    levels, rest = [], np.arange(len(words))
    while len(rest):
        size = max(64, int(LOAD * len(rest)))
        at = _place(words[rest], len(levels), size)
        hits = np.bincount(at.astype(np.int64), minlength=size)
        levels.append(hits == 1)
        rest = rest[hits[at.astype(np.int64)] > 1]
    return levels


def slots_of(levels: list[np.ndarray], words: np.ndarray) -> np.ndarray:
    """Slot of each digest: 0..n-1 without gaps for members; -1 or any slot for others."""
    slot, rest, base = np.full(len(words), -1, np.int64), np.arange(len(words)), 0
    for k, bits in enumerate(levels):
        at = _place(words[rest], k, len(bits)).astype(np.int64)
        hit = bits[at]
        slot[rest[hit]] = base + np.cumsum(bits)[at[hit]] - 1
        base += int(bits.sum())
        rest = rest[~hit]
    return slot


def _blob(column: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(column), np.uint8).reshape(-1, 32)


def _shard(groups: DataFrame, n: int) -> DataFrame:
    return groups.withColumn("shard", F.pmod(F.xxhash64("digest"), F.lit(n)))


def _grouped(rows: DataFrame) -> DataFrame:
    return rows.groupBy("digest").agg(F.min("doc_id").alias("winner"), F.count(F.lit(1)).alias("copies"))


INDEX = "shard long, n long, bits binary, sizes binary, digests binary, winners binary, named binary, copies binary"


def build_index(history: DataFrame, shards: int) -> DataFrame:
    """One row per shard of the minimal perfect hash over the distinct digests of ``history`` (doc_id, digest)."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        words = _words(_blob(pdf["digest"]))
        levels = build_levels(words)
        order = np.argsort(slots_of(levels, words))
        ids, named = pdf["winner"].fillna(0).to_numpy(np.int64), pdf["winner"].notna().to_numpy()
        return pd.DataFrame([{"shard": int(pdf["shard"].iloc[0]), "n": len(pdf), "bits": np.packbits(np.concatenate(levels)).tobytes(), "sizes": np.array([len(x) for x in levels], np.int64).tobytes(), "digests": words[order].tobytes(), "winners": ids[order].tobytes(), "named": named[order].tobytes(), "copies": pdf["copies"].to_numpy(np.int64)[order].tobytes()}])

    return _shard(_grouped(history), shards).groupBy("shard").applyInPandas(build, INDEX)


def _levels(row: pd.Series) -> list[np.ndarray]:
    sizes = np.frombuffer(row["sizes"], np.int64)
    return np.split(np.unpackbits(np.frombuffer(row["bits"], np.uint8))[: sizes.sum()].astype(bool), np.cumsum(sizes)[:-1])


FOUND = "digest binary, winner long, copies long, member boolean"


def look_up(incoming: DataFrame, index: DataFrame, shards: int, rest_of_index: bool = True) -> DataFrame:
    """Groups of distinct digests after adding ``incoming`` (doc_id, digest) to what the index knows.

    ``member`` tells whether the index held the digest, checked on all its
    bytes. With ``rest_of_index`` the index's digests that nothing asked for
    are returned too.
    """

    def probe(key: tuple, asked: pd.DataFrame, shard: pd.DataFrame) -> pd.DataFrame:
        none = pd.DataFrame({"digest": [], "winner": [], "copies": [], "member": []})
        if not len(shard):
            return asked.assign(member=False)[["digest", "winner", "copies", "member"]] if len(asked) else none
        row = shard.iloc[0]
        held, ids, named, copies = _words(np.frombuffer(row["digests"], np.uint8)), np.frombuffer(row["winners"], np.int64), np.frombuffer(row["named"], bool), np.frombuffer(row["copies"], np.int64)
        touched = np.zeros(len(held), bool)
        parts = []
        if len(asked):
            words = _words(_blob(asked["digest"]))
            slot = slots_of(_levels(row), words)
            member = (slot >= 0) & (held[slot] == words).all(1)
            own = slot[member]
            touched[own] = True
            winner = asked["winner"].astype("Int64").reset_index(drop=True)
            known = pd.Series(ids[own], dtype="Int64").where(pd.Series(named[own]))
            winner[member] = pd.concat([winner[member].reset_index(drop=True), known], axis=1).min(axis=1).to_numpy()
            total = asked["copies"].to_numpy(np.int64).copy()
            total[member] += copies[own]
            parts.append(pd.DataFrame({"digest": asked["digest"].to_numpy(), "winner": winner.to_numpy(), "copies": total, "member": member}))
        if rest_of_index and (left := np.flatnonzero(~touched)).size:
            parts.append(pd.DataFrame({"digest": [held[i].tobytes() for i in left], "winner": pd.Series(ids[left], dtype="Int64").where(pd.Series(named[left])).to_numpy(), "copies": copies[left], "member": True}))
        return pd.concat(parts) if parts else none

    return _shard(_grouped(incoming), shards).groupBy("shard").cogroup(index.groupBy("shard")).applyInPandas(probe, FOUND)


def dedup(docs: DataFrame, history: str = "crc32(cast(doc_id AS string)) % 2 = 0", shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Every row with the id of the row that stays among equal texts.

    ``history`` splits the corpus into the indexed part and the part that is
    looked up in it; the result doesn't depend on the split, as a winner is the
    smallest id on either side.
    """
    rows = cut(digests(docs).withColumn("old", F.coalesce(F.expr(history), F.lit(True))))
    shards = max(1, -(-rows.count() // shard_rows))
    index = build_index(rows.where("old"), shards)
    groups = look_up(rows.where("NOT old"), index, shards)
    # The hot digests' rows meet their single group row; skewed partitions are split at run time.
    out = rows.join(groups, "digest")
    return out.select("doc_id", F.col("winner").alias("keep_id"), F.col("copies").alias("group_size"), F.col("doc_id").eqNullSafe(F.col("winner")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), "member")


def keep_one(docs: DataFrame) -> DataFrame:
    """The documents (all columns) without those whose text one with a smaller doc_id has; one of repeated rows."""
    found = dedup(docs).where("kept").groupBy("doc_id", "text_sha256").agg((F.count(F.lit(1)) > 1).alias("again"))
    # Columns stay inside ``row``, so that no name clashes.
    rows = docs.select(F.struct("*").alias("row"), F.struct("doc_id", text_digest(F.col("text")).alias("sha")).alias("id"))
    met = rows.join(found.select(F.struct("doc_id", F.col("text_sha256").alias("sha")).alias("of"), "again"), F.col("id").eqNullSafe(F.col("of")))
    kept = met.where(~F.col("again")).select("row").unionByName(met.where("again").dropDuplicates(["id"]).select("row"))
    return kept.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))


SQL = r"""
WITH d AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
