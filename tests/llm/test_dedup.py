"""Exact, near and substring dedup against brute force, with the edge cases of their tables."""

import hashlib
import itertools
import math
import re

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from shapesig.llm import exact_dedup, near_copies, simhash_dedup, substring_dedup
from shapesig.llm.graph import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = {c: c + 32 for c in range(65, 91)}


def docs(spark, texts, ids=None):
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in zip(ids or range(len(texts)), texts, strict=True)], SCHEMA)


def prose(n, seed, words=400):
    rng = np.random.default_rng(seed)
    return " ".join(f"w{x}" for x in rng.integers(0, words, n))


ODD = [None, "", "  \n", "One", "one two", "One  two\tthree", "one two three", "É x\x1cy \x85 z", prose(3000, 1), prose(3000, 1), "a" * 50_000]


def brute_fingerprint(text):
    w = WORDS.findall((text or "").translate(LOWER))
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def test_fingerprints_and_components(spark):
    texts = [*ODD, *(prose(200, 7) + f" tail{i}" for i in range(30)), *(prose(60, i) for i in range(40))]
    got = {r.doc_id: r for r in simhash_dedup.near_duplicates(docs(spark, texts)).collect()}
    fp = [brute_fingerprint(t) for t in texts]
    root = list(range(len(texts)))
    for i, j in itertools.product(range(len(texts)), repeat=2):
        if (fp[i] ^ fp[j]).bit_count() <= 2 and root[i] != root[j]:
            a, b = sorted((root[i], root[j]))
            root = [a if x == b else x for x in root]
    assert all(int(got[i].fingerprint, 16) == fp[i] and got[i].component_id == root[i] for i in range(len(texts)))


@pytest.mark.parametrize("radius,dense", [(2, 1), (3, 64)])
def test_links_lose_nothing(spark, dense, radius):
    rng = np.random.default_rng(radius)
    base = rng.integers(0, 1 << 63, 12)
    prints = {int(b) for b in base} | {int(b) ^ (1 << int(i)) ^ (1 << int(j)) for b in base for i, j in rng.integers(0, 63, (25, 2))}
    nodes = spark.createDataFrame([(x,) for x in prints], "fp long")
    got = {r.node: r.root for r in components(simhash_dedup.links(nodes, radius, dense)).collect()}
    root = {x: x for x in prints}
    for a, b in itertools.combinations(sorted(prints), 2):
        if (a ^ b).bit_count() <= radius and root[a] != root[b]:
            low, high = sorted((root[a], root[b]))
            root = {k: low if v == high else v for k, v in root.items()}
    assert {x: got.get(x, x) for x in prints} == root


def test_plan_meets_the_general_pigeonhole():
    both = np.full((64, 64), 2500) + np.diag([2500] * 64)
    for n in (0, 1, 10, 10**6, 10**10):
        for radius in (1, 2, 4, 8):
            parts = simhash_dedup.plan(n, both * n // 10_000, radius)
            assert radius > 4 or sum(math.comb(len(p.bits), r) for p in parts for r in range(p.radius + 1)) < 2000
            rng = np.random.default_rng(1)
            for _ in range(300):
                x = sum(1 << int(b) for b in rng.choice(64, rng.integers(0, radius + 1), replace=False))
                assert any((x & p.mask).bit_count() <= p.radius for p in parts)


def test_components_of_long_paths_and_stars(spark):
    edges = [(i, i + 1) for i in range(60)] + [(100, 100 + i) for i in range(1, 50)] + [(201, 200), (7, 7)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert {got[i] for i in range(61)} == {0} and {got[100 + i] for i in range(50)} == {100} and got[201] == 200
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def kept_of(spark, texts, **how):
    gone = near_copies.groups(docs(spark, texts), **how).where("least < doc_id").select("doc_id").collect()
    return set(range(len(texts))) - {r.doc_id for r in gone}


def test_near_copies_keep_the_first(spark):
    base = [prose(300, s, 5000) for s in range(20)]
    texts = base + [" ".join(w if k != 150 else "changed" for k, w in enumerate(b.split())) for b in base[:10]] + [None, "", "short", "Short"]
    clash = docs(spark, texts).selectExpr("*", "1 AS node", "2 AS spot", "'x' AS s", "3 AS n", "4 AS slice", "5 AS least")
    kept = near_copies.keep_one(clash)
    assert kept.columns == clash.columns and {r.doc_id for r in kept.collect()} == set(range(20)) | {30, 32}
    assert near_copies.keep_one(docs(spark, [])).count() == 0


def test_repeated_and_null_ids_of_near_copies(spark):
    a, b, long = prose(50, 1, 5000), prose(50, 2, 5000), prose(400_000, 3, 100_000)
    df = docs(spark, [a, b, b + " x", a + " x", a, b, long, long + " y"], [5, 5, 9, 7, None, None, 20, 21])
    assert sorted(str(r.doc_id) for r in near_copies.keep_one(df).collect()) == ["20", "5", "5", "None", "None"]


def brute_kept(texts):
    sets = [{tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for w in (t.lower().split() for t in texts)]
    root = list(range(len(sets)))
    for a, b in itertools.combinations(root[:], 2):
        if root[a] != root[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
            low, high = sorted((root[a], root[b]))
            root = [low if r == high else r for r in root]
    return {i for i, r in enumerate(root) if r == i}


def moved(words, places):
    """The words with the pairs at these places exchanged: the same distinct words, other shingles."""
    words = list(words)
    for k in places:
        words[k], words[k + 1] = words[k + 1], words[k]
    return " ".join(words)


def test_a_hub_under_the_similarity_hides_no_copies(spark):
    base = [f"w{i}" for i in np.random.default_rng(8).permutation(300)]
    hub = moved(base, [5 + 37 * i for i in range(7)])
    crowd = [hub, *(moved(base, [20 + k]) for k in range(0, 260, 3) if k % 37 > 4)]
    kept = brute_kept(crowd)
    assert kept == {0, 1} and kept_of(spark, crowd) == kept


@pytest.mark.parametrize("how", [{}, {"weight": 60, "slice_bytes": 300, "buckets": 3}, {"weight": 400, "radius": 0, "buckets": 1}])
def test_chains_and_separate_groups_that_share_passages(spark, how):
    shared = prose(20, 7, 5000)
    texts = [prose(40, s, 5000) + " " + shared + (" end" if k else "") for s in range(6) for k in range(2)]
    base = prose(120, 90, 5000).split()
    texts += [moved(base, range(3, 3 + 24 * k, 24)) for k in range(5)]  # each is alike to the next one only
    kept = brute_kept(texts)
    assert kept == {*range(0, 12, 2), 12} and kept_of(spark, texts, **how) == kept


def test_rows_that_come_out_do_not_grow_with_pairs():
    rng = np.random.default_rng(1)
    for crowd in (40, 160):
        sets = [np.unique(np.concatenate([np.arange(70), rng.integers(1000, 10**9, 30)])) for _ in range(crowd)]
        sets += [np.append(sets[0], 7 * 10**9 + k) for k in range(crowd)]
        a, b = near_copies._settled(np.arange(len(sets)), sets, 0.8)
        assert len(a) == crowd and {0, *range(crowd, 2 * crowd)} == {*a, *b}


def edited(words, kind, rng):
    """A copy of 5-word similarity just over 0.8."""
    n, some = len(words), [f"v{x}" for x in rng.integers(0, 10**6, len(words))]
    cut = int(0.18 * (n - 4))
    at = int(rng.integers(5, n - cut))
    block = int(0.09 * n) - 4
    return {"appended": [*words, *some[:cut]], "cut": words[:-cut], "block": [*words[:at], *some[:block], *words[at + block :]]}[kind]


def test_appended_cut_and_block_edited_copies_are_all_found(spark):
    rng = np.random.default_rng(21)
    texts = []
    for i in range(60):
        words = prose(int(rng.integers(80, 400)), 300 + i, 10**6).split()
        texts += [" ".join(words), " ".join(edited(words, ("appended", "cut", "block")[i % 3], rng))]
    kept = brute_kept(texts)
    assert kept == set(range(0, 120, 2))
    assert {r.doc_id for r in near_copies.keep_one(docs(spark, texts)).collect()} == kept


def test_packed_numbers_come_back():
    rng = np.random.default_rng(5)
    for n in (0, 1, 1000):
        for width in (4, 6):
            v = rng.integers(0, 1 << 8 * width, n).astype(np.uint64)
            for x in (v, np.sort(v)):
                assert np.array_equal(near_copies.unpacked(near_copies.packed(x, width), width), x)


def test_prefixes_of_similar_sets_meet_in_any_order():
    rng = np.random.default_rng(4)
    for i in range(60):
        words = prose(int(rng.integers(60, 200)), i, 10**6).split()
        _, n, h = near_copies.sets_of(pa.array([" ".join(words), " ".join(edited(words, ("appended", "cut", "block")[i % 3], rng))]))
        doc = np.repeat([0, 1], n)
        _, place, times = np.unique(h, return_inverse=True, return_counts=True)
        for levels in (times, rng.integers(0, 9, len(times))):
            able, chosen = near_copies.prefix(n, doc, h, times[place] > 1, levels[place].astype(np.uint8), 0.8)
            assert able.all() and set(h[chosen & (doc == 0)]) & set(h[chosen & (doc == 1)])


def test_perfect_hash_has_no_gaps_and_knows_strangers():
    rng = np.random.default_rng(3)
    words = rng.integers(0, 1 << 63, (5000, 4)).astype(np.uint64)
    levels = exact_dedup.build_levels(words)
    assert sorted(exact_dedup.slots_of(levels, words)) == list(range(5000))
    held = np.empty_like(words)
    held[exact_dedup.slots_of(levels, words)] = words
    other = rng.integers(0, 1 << 63, (5000, 4)).astype(np.uint64)
    slot = exact_dedup.slots_of(levels, other)
    assert not ((slot >= 0) & (held[slot] == other).all(1)).any()


def test_exact_dedup(spark):
    texts = ["a b", "a  b", "a\tb", "x", None, "", " ", "a b ", "solo", *["hot"] * 300]
    ids = [5, 3, 9, 1, 8, 2, 11, 4, 6, *range(100, 400)]
    norm = [re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for t in texts]
    for history in ("doc_id % 2 = 0", "doc_id % 2 = 1", "true", "false"):
        got = {r.doc_id: r for r in exact_dedup.dedup(docs(spark, texts, ids), history, shard_rows=3).collect()}
        for i, n in zip(ids, norm, strict=True):
            group = [j for j, m in zip(ids, norm, strict=True) if m == n]
            assert (got[i].keep_id, got[i].group_size, got[i].kept, got[i].text_sha256) == (min(group), len(group), i == min(group), hashlib.sha256(n.encode()).hexdigest())
    assert exact_dedup.dedup(docs(spark, [])).count() == 0


def test_exact_dedup_keeps_one_of_repeated_rows(spark):
    df = docs(spark, ["a", "a", "a", "b", "b"], [1, 1, 2, 3, None])
    assert sorted(map(str, ((r.doc_id, r.text) for r in exact_dedup.keep_one(df).collect()))) == ["(1, 'a')", "(3, 'b')"]
    other = docs(spark, ["a", "b"], [1, 1])
    assert exact_dedup.keep_one(other).count() == 2


def brute_repeats(rows):
    words = {i: WORDS.findall(t or "") for i, t in rows}
    first = {}
    for i in sorted(words):
        for k in range(len(words[i]) - 12):
            first.setdefault(tuple(words[i][k : k + 13]), i)
    out = {}
    for i, w in words.items():
        gone = set()
        for k in range(len(w) - 12):
            if first[tuple(w[k : k + 13])] < i:
                gone.update(range(k, k + 13))
        out[i] = (len(w), len(gone), hashlib.sha256(" ".join(x for k, x in enumerate(w) if k not in gone).encode()).hexdigest())
    return out


@pytest.mark.parametrize("blocks", [1, 7])
def test_substring_dedup(spark, blocks):
    passage, rng = prose(20, 50), np.random.default_rng(0)
    texts = [*ODD, *(f"{prose(int(rng.integers(0, 30)), i)} {passage} {prose(int(rng.integers(0, 30)), i + 500)}" for i in range(40)), *(passage.rsplit(" ", k)[0] for k in range(9)), prose(13, 9), prose(13, 9), "r " * 40, "r " * 15]
    rows = list(enumerate(texts))
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.remove_repeats(docs(spark, texts), blocks).collect()}
    assert got == brute_repeats(rows)


def test_substring_dedup_edges(spark):
    long = prose(40, 3)
    got = sorted(((r.doc_id, r.n_removed, r.kept) for r in substring_dedup.remove_repeats(docs(spark, [long, long, long, None], [4, 4, None, 1]), 2, with_text=True).collect()), key=str)
    assert got == [(1, 0, ""), (4, 0, long), (4, 0, long), (None, 40, "")]
    assert substring_dedup.remove_repeats(docs(spark, []), 2).count() == 0
    clash = docs(spark, [long]).selectExpr("*", "1 AS block", "2 AS bucket", "'x' AS keys")
    assert substring_dedup.remove_repeats(clash).count() == 1


def test_cover_aligns_any_two_places():
    for i, j in itertools.product(range(substring_dedup.PERIOD), repeat=2):
        assert any((i + d) % substring_dedup.PERIOD in substring_dedup.COVER and (j + d) % substring_dedup.PERIOD in substring_dedup.COVER for d in range(substring_dedup.PERIOD))
