"""Searches, measures and experiments on the smallest tables, against DuckDB and invariants."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as E
from shapesig import reports, workloads
from shapesig.functions import sqlfuncs
from shapesig.operators import index as ix
from shapesig.operators import measures as M
from shapesig.operators import prepare as P
from shapesig.operators import search as S
from shapesig.operators.signature import signature
from shapesig.plans import planner

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["w5_sig_doc", "w7_cand_cust_m3", "w8_knn_exact_emb", "w8_knn_exact_box_acct", "w9_knn_approx_cust_sized_m3", "w11_w12_recall_pruning_doc_sized", "w13_length_sweep", "w17_theorem2_box_part", "w18_bands_1_vs_2", "w19_precheck_ablation", "w20_bounds_lossless", "w22_near_dup_docs", "w23_filtered_knn", "w24_nation_rollup", "w25_cross_bench", "w27_wkt_roundtrip", "g9_hull_cust", "m10b_nearest_set", "m13_range_search"])
def test_experiment_equals_sql(spark, duck, same, name):
    same(workloads.queries()[name](spark, SF), duck.sql(workloads.oracle_sql()[name]))


@pytest.mark.parametrize("name", sorted(reports.queries()))
def test_report_equals_sql(spark, duck, same, name):
    same(reports.queries()[name](spark, SF), duck.sql(reports.oracle_sql()[name]))


@pytest.fixture(scope="module")
def doc(spark):
    poly = workloads.prepared(spark, SF, "doc")
    return poly, workloads.query_set(poly), P.global_frame(poly)


def test_candidates_shrink_with_length_and_grow_with_bands(doc):
    poly, q, frame = doc
    got = {(m, b): set(map(tuple, S.candidate_pairs(poly, q, frame, m, b, 256).collect())) for m in (1, 2, 3) for b in (1, 2)}
    for b in (1, 2):
        assert got[(1, b)] >= got[(2, b)] >= got[(3, b)]
    assert all(got[(m, 1)] <= got[(m, 2)] for m in (1, 2, 3))


def test_approximate_distances_are_exact_and_recall_is_a_share(doc):
    poly, q, frame = doc
    exact, approx = S.knn_exact(poly, q, None, most=1.0), S.knn_approx(poly, q, frame, 10, 2, 2, 256)
    assert approx.join(exact.withColumnRenamed("jd", "e"), ["qid", "pid"]).where("jd <> e").count() == 0
    top = S.top_k(exact, 10)
    r = {x.k: x.recall for x in M.recall_at_k(approx, top, [1, 10]).collect()}
    ties = {x.k: x.recall for x in M.recall_at_k(approx, top, [1, 10], ties=True).collect()}
    assert all(0 <= v <= 1 for v in r.values()) and all(ties[k] >= r[k] for k in r)
    assert {x.k: x.recall for x in M.recall_at_k(top, top, [1, 10]).collect()} == {1: 1.0, 10: 1.0}
    assert all(0 <= x.hit_rate <= 1 for x in M.hit_rate_at_k(approx, top, [10]).collect())


def test_longer_codes_bring_nearer_candidates(doc):
    poly, q, frame = doc
    means = [S.refine(S.candidate_pairs(poly, q, frame, m, 2, 256), poly, q).agg(F.avg("jd")).first()[0] for m in (1, 3, 5)]
    assert means == sorted(means, reverse=True)


def test_equal_shapes_always_meet(spark):
    poly = workloads.prepared(spark, SF, "doc")
    _, members = S.same_shapes(poly)
    index = ix.bucket_index(signature(poly, P.global_frame(poly), 5, 2, 256), 5, 2)
    kinds = index.join(members, "pid").groupBy("band", "cls").agg(F.countDistinct("code").alias("n"))
    assert kinds.where("n > 1").count() == 0


def test_stored_index_and_salting_give_the_same_candidates(spark, doc, tmp_path):
    poly, q, frame = doc
    index = ix.bucket_index(signature(poly, frame, 2, 2, 256), 2, 2)
    ix.save(index, frame, str(tmp_path / "index"), files=4)
    stored, kept = ix.load(spark, str(tmp_path / "index"))
    assert kept == frame
    probes = index.join(q.select("pid"), "pid", "left_semi")
    want = set(map(tuple, ix.candidates(probes, index).collect()))
    assert want == set(map(tuple, ix.candidates(probes, stored, how="merge").collect())) == set(map(tuple, planner.salted_candidates(probes, index, 3).collect()))


def test_query_blocks_split_large_query_sets(doc):
    poly, q, _ = doc
    a, b = S.knn_exact(poly, q, 5).collect(), None
    old, S.query_blocks.__defaults__ = S.query_blocks.__defaults__, (500,)
    try:
        assert len(S.query_blocks(q)) > 1
        b = S.knn_exact(poly, q, 5).collect()
    finally:
        S.query_blocks.__defaults__ = old
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))


def test_self_join_by_buckets_is_part_of_the_exact_one(doc):
    poly, _, frame = doc
    exact = set(map(tuple, S.self_join(poly, 0.1).collect()))
    some = set(map(tuple, S.self_join(poly, 0.1, frame, 2, 2, 256).collect()))
    assert some <= exact and len(some) >= 0.6 * len(exact)


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    frame = sqlfuncs.views(spark, SF, "box_part", 2)
    assert spark.sql("SELECT count(*) FROM v_box_part WHERE abs(ring_area(ring) - area2 / 2) > 0.01 OR ring_jaccard(ring, ring) < 0.999999 OR NOT ring_contains(ring, 1L, 1L)").first()[0] == 0
    assert spark.sql(f"SELECT * FROM sample_points({frame.xmin}L, {frame.xmax}L, {frame.ymin}L, {frame.ymax}L, 2, 5)").count() == 10
    assert spark.sql("SELECT i.band, i.code FROM v_box_part_index i JOIN (SELECT p.band, p.code FROM v_box_part_sig s, LATERAL probe(s.sig, 2) p) x USING (band, code) LIMIT 1").count() == 1
    sig = spark.table("v_box_part").select("pid", sqlfuncs.ring_signature(frame, 2)("ring").alias("s")).join(spark.table("v_box_part_sig"), "pid")
    assert sig.where("s <> sig").count() == 0


def test_index_is_tuned_to_recall(spark):
    r = workloads.queries()["tuned_index_doc"](spark, SF).first()
    assert r.recall >= 0.9


def test_entry(spark):
    assert E.entry(spark).columns == ["qid", "rank", "pid", "jd"]
    assert set(E.oracle_sql()) <= set(E.queries())


def test_choice():
    assert planner.choose(10**6, 100, 12, 6, 20).form == "arrow"
    assert planner.choose(10**6, 100, 12, 6, 20, in_jvm=True).form == "grid"
    assert planner.choose(10, 10**9, 12, 6, 20, largest_bucket=5_000_000) == planner.Choice("arrow", False, False, 5)


def test_clusters_are_components(spark):
    from shapesig.operators.cluster import clusters

    edges = [(i, i + 1) for i in range(30)] + [(100, 100 + i) for i in range(1, 20)] + [(201, 200), (7, 7)]
    got = {r.node: r.cluster for r in clusters(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert {got[i] for i in range(31)} == {0} and {got[100 + i] for i in range(20)} == {100} and got[201] == got[200] == 200
    assert clusters(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.mark.parametrize("name", ["m6b_open_slots", "m14_clusters", "a17_mean_distance", "g10_monte_carlo", "m11_estimated_jaccard", "j_probe_merge"])
def test_later_experiment_equals_sql(spark, duck, same, name):
    same(workloads.queries()[name](spark, SF), duck.sql(workloads.oracle_sql()[name]))
