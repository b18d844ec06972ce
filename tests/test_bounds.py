"""Searches that spare work by what shapes hold of a grid's cells: nothing is lost, and pairs stay in their task."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from shapesig import workloads
from shapesig.functions.kernels import Celled, Grid, Rings, distances, plain_rings
from shapesig.operators import index as ix
from shapesig.operators import prepare as P
from shapesig.operators import search as S
from shapesig.operators.signature import contained, holding, signature

SF = "/root/testdata/sf0.001"


def stars(n, seed=1):
    rng = np.random.default_rng(seed)
    turn = np.sort(rng.uniform(0, 2 * np.pi, (n, 10)), 1)
    r = rng.uniform(200, 2000, (n, 10)) * rng.uniform(0.5, 1, (n, 1))
    x, y = (2 * np.rint(r * f(turn) / 2).astype(np.int64).reshape(-1) for f in (np.cos, np.sin))
    return x, y, np.arange(n + 1) * 10


@pytest.fixture(scope="module")
def plan():
    return lambda df: df._jdf.queryExecution().executedPlan().toString()


def test_cells_spare_only_what_is_too_far():
    x, y, starts = stars(1500)
    rings = Rings(x, y, starts)
    held = Celled(rings, Grid(x[:400], y[:400], 2))
    met = 0
    for k in range(0, 1500, 100):
        d = distances(held.rings, held.rings, k)
        limit = np.sort(d)[20]
        at, most = held.near(held, k, limit)
        assert set(np.flatnonzero(d <= limit)) <= set(at) and (most >= 1 - d[at] - 1e-6).all()
        some = np.arange(0, 1500, 7)
        assert set(some[d[some] <= limit]) <= set(held.near(held, k, limit, some)[0]) <= set(some)
        met += len(at)
    assert met < 15 * 1500 / 10


def test_rings_that_wind_twice_or_cross_are_never_spared():
    square, bow = [(0, 0), (40, 0), (40, 40), (0, 40)], [(0, 0), (40, 40), (40, 0), (0, 60)]
    twice = [(0, 0), (40, 0), (40, 40), (0, 40), (0, 0), (20, 0), (20, 20), (0, 20)]
    far = [(900, 900), (940, 900), (940, 940), (900, 940)]
    rings = Rings.of([[{"x": a, "y": b} for a, b in r] for r in (square, bow, twice, far)])
    assert plain_rings(rings).tolist() == [True, False, False, True]
    held = Celled(rings, Grid(np.array([0, 40]), np.array([0, 40]), 2))
    odd = set(np.flatnonzero(np.isin(held.order, (1, 2))))
    for k in range(4):
        assert odd <= set(held.near(held, k, 0.0)[0])
    for k in odd:
        assert len(held.near(held, k, 0.0)[0]) == 4


@pytest.mark.parametrize("name", ["cust_sized", "doc", "user", "cust_bal"])
def test_spared_search_equals_brute_force(spark, name):
    poly = workloads.prepared(spark, SF, name)
    q = poly.where("pid % 10 = 0")
    for k, most in ((3, None), (50, None), (None, 0.3)):
        a, b = (sorted(map(tuple, S.knn_exact(poly, q, k, bounds=on, most=most).collect())) for on in (True, False))
        assert a == b
    every = S.nearest_set(S.knn_exact(poly, q, None, bounds=False, most=1.0))
    ties = S.nearest_set(S.knn_exact(poly, q, 1, ties=True))
    assert sorted(map(tuple, every.select("qid", "pid", "jd").collect())) == sorted(map(tuple, ties.select("qid", "pid", "jd").collect()))


def test_candidates_of_several_lengths_in_one_pass_equal_the_join(spark):
    poly = workloads.prepared(spark, SF, "cust")
    q, frame = workloads.query_set(poly), P.global_frame(poly)
    found = S.nearest(poly, q, 7, True, frame, (1, 2, 4), 3, 512)
    for m in (1, 2, 4):
        index = ix.bucket_index(signature(poly, frame, m, 3, 512), m, 3)
        cand = ix.candidates(ix.bucket_index(signature(q, frame, m, 3, 512), m, 3), index)
        want = S.top_k(S.refine(cand, poly, q), 7).select("qid", "pid", "jd")
        got = S.top_k(found.where((F.col("m") == m) & F.col("qid").isNotNull()), 7).select("qid", "pid", "jd")
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
        assert found.where((F.col("m") == m) & F.col("qid").isNull()).agg(F.sum("cands")).first()[0] == cand.count()


def test_searches_shuffle_no_candidate_pairs(spark, plan):
    for name in ("w9_knn_approx_cust_m1", "w9_knn_approx_doc_m3"):
        assert "Join" not in plan(workloads.queries()[name](spark, SF))


def test_the_checkpoint_of_a_search_has_no_column_that_it_does_not_read(spark, plan):
    for name in ("w9_knn_approx_cust_m1", "w9_knn_approx_doc_m3"):
        scan = plan(workloads.queries()[name](spark, SF)).split("Scan ExistingRDD", 1)[1]
        assert "ring#" in scan and "cx#" not in scan and "area2#" not in scan


def test_a_task_hands_on_k_rows_a_query_however_many_candidates_it_met(spark):
    poly = workloads.prepared(spark, SF, "cust")
    q, k = workloads.query_set(poly), 3
    found = S.nearest(poly, q, k, False, P.global_frame(poly), (1,)).withColumn("task", F.spark_partition_id())
    rows = found.where("qid IS NOT NULL").groupBy("task", "qid").count().agg(F.max("count"), F.sum("count")).first()
    met = found.where("qid IS NULL").agg(F.sum("cands")).first()[0]
    assert rows[0] <= k and met > 2 * rows[1]


def test_all_pairs_of_the_first_law_stay_in_their_tasks(spark, duck, same, plan):
    for name in ("w16_theorem1_cust", "w16_theorem1_emb"):
        got = workloads.queries()[name](spark, SF)
        assert "Join" not in plan(got)
        same(got, duck.sql(workloads.oracle_sql()[name]))


def test_held_points_row_by_row_equal_the_join(spark):
    from shapesig.functions.draws import samples

    poly = workloads.prepared(spark, SF, "doc")
    frame = P.global_frame(poly)
    joined = contained(poly, F.broadcast(samples(spark, frame, [0], 1, 64)))
    alone = holding(poly, frame, 0, 64).select("pid", F.lit(0).alias("slot"), F.explode("attempts").alias("attempt"))
    assert sorted(map(tuple, joined.collect())) == sorted(map(tuple, alone.collect()))


def copied(spark, name, times):
    """A layer and its copies, ids shifted: each ring is asked for by several queries."""
    poly = workloads.prepared(spark, SF, name)
    return workloads.settle(poly.crossJoin(spark.range(times)).withColumn("pid", F.col("pid") + 100000 * F.col("id")).drop("id"))


def test_queries_of_one_ring_are_met_once_and_lose_nothing(spark):
    poly = copied(spark, "cust", 6)
    q, frame = poly.where("pid % 10 = 0"), P.global_frame(poly)
    index, probes = (ix.bucket_index(signature(p, frame, 1, 2), 1, 2) for p in (poly, q))
    cand = ix.candidates(probes, index)
    n = q.count()
    for k in (1, 3, 9):
        assert sorted(map(tuple, S.knn_approx(poly, q, frame, k, 1).collect())) == sorted(map(tuple, S.top_k(S.refine(cand, poly, q), k).collect()))
        for own in (True, False):
            a, b = (sorted(map(tuple, S.knn_exact(poly, q, k, own, bounds=on).collect())) for on in (True, False))
            assert a == b and len(a) == n * k
    a, b = (sorted(map(tuple, S.knn_exact(poly, q, None, bounds=on, most=0.3).collect())) for on in (True, False))
    assert a == b
    found = S.nearest(poly, q, 3, False, frame, (1,))
    assert found.where("qid IS NULL").agg(F.sum("cands")).first()[0] == cand.count()
    every = S.nearest_set(S.knn_exact(poly, q, None, bounds=False, most=1.0)).select("qid", "pid", "jd")
    assert sorted(map(tuple, every.collect())) == sorted(map(tuple, S.nearest_set(S.knn_exact(poly, q, 1, ties=True)).select("qid", "pid", "jd").collect()))
    # Not 3 rows for each query and task, of which there are 4 at least.
    assert found.where("qid IS NOT NULL").count() <= 4 * n and poly.rdd.getNumPartitions() >= 4
    assert sum(len(b.once()) for b in S.query_blocks(q)) * 6 == n


def test_a_search_gathers_its_shapes_in_as_many_tasks_as_cores(spark):
    poly = workloads.settle(workloads.prepared(spark, SF, "cust_sized").repartition(23))
    q = workloads.query_set(poly)
    found = S.nearest(poly, q, 5, True, P.global_frame(poly), (2,))
    assert found.rdd.getNumPartitions() <= spark.sparkContext.defaultParallelism < 23
    exact = S.top_k(found.where("m = 0"), 5)
    assert sorted(map(tuple, exact.collect())) == sorted(map(tuple, S.knn_exact(poly, q, 5, bounds=False).collect()))


def test_gathered_batches_hold_the_same_rows_in_order():
    parts = [pa.record_batch({"pid": list(range(a, b))}) for a, b in ((0, 3), (3, 3), (3, 11), (11, 12))]
    got = list(S.gathered(iter(parts), 5))
    assert [b.num_rows for b in got] == [5, 5, 2] and [v for b in got for v in b.column(0).to_pylist()] == list(range(12))
    assert not list(S.gathered(iter(parts[1:2]), 5))
