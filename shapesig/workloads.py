"""The experiments on the given tables, and their SQL.

Every search takes as queries the shapes whose id is divisible by 50, against all
shapes of the layer. Plain and sized layers are reported side by side.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shapesig import oracles as O
from shapesig.functions import geometry as G
from shapesig.functions.draws import samples
from shapesig.operators import index as ix
from shapesig.operators import measures as M
from shapesig.operators import prepare as P
from shapesig.operators import search as S
from shapesig.operators.cluster import clusters
from shapesig.operators.signature import attempt_costs, first_hit, holding, signature, slots_of
from shapesig.session import settle, table
from shapesig.sources import layers, wkt

Query = Callable[[SparkSession, str], DataFrame]
KS = [10, 50, 100]
#: Attempts that the table forms, and the first pass of the SQL, draw for all shapes; searches have no cap.
PLAIN_CAP, SIZED_CAP = 256, 4096


def cap_of(name: str) -> int:
    return SIZED_CAP if name in layers.SIZED else PLAIN_CAP


#: What a search through buckets reads of a layer.
SEARCHED = ("pid", "ring", "box")


def prepared(spark: SparkSession, sf_dir: str, name: str, builder: str = "star", columns: tuple[str, ...] = ("*",)) -> DataFrame:
    """The layer, or these columns of it, settled: several steps read it. A small one is dealt to all cores, for its shapes are few bytes and much work."""
    poly, cores = settle(layers.build(spark, sf_dir, name, builder).select(*columns)), spark.sparkContext.defaultParallelism
    return settle(poly.repartition(cores)) if poly.rdd.getNumPartitions() < cores else poly


def query_set(poly: DataFrame) -> DataFrame:
    return poly.where(F.col("pid") % O.QUERY_STEP == 0)


def search(spark: SparkSession, sf_dir: str, name: str, m: int, bands: int, k: int, base_seed: int = 42) -> DataFrame:
    poly = prepared(spark, sf_dir, name, columns=SEARCHED)
    return S.knn_approx(poly, query_set(poly), P.global_frame(poly), k, m, bands, None, base_seed)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(spark, sf_dir, "doc", 3, 2, 10)


# ---- layers, frame, points


def layer_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in PROFILED:
        p = layers.build(spark, sf_dir, name)
        row = p.agg(F.count(F.lit(1)).alias("shapes"), F.sum(F.when(F.col("pid") % O.QUERY_STEP == 0, 1).otherwise(0)).alias("queries"), F.round(F.avg(F.size("ring")), 6).alias("mean_points"), F.sum(F.octet_length(G.to_wkt(F.col("ring")))).alias("wkt_bytes")).select(F.lit(name).alias("layer"), "*")
        out = row if out is None else out.unionByName(row)
    return out


PROFILED = ("cust", "flag", "supp", "emb", "user", "doc", "order", "part", "box_part", "box_acct", "page", "turn", "bench", "cust_sized", "flag_sized", "supp_sized", "emb_sized", "doc_sized", "cust_bal")


def _profile_sql() -> str:
    ctes: O.Cte = []
    rows = []
    for name in PROFILED:
        ctes += O.prepared(name, f"{name}__")
        rows.append(f"SELECT '{name}' AS layer, count(*) AS shapes, sum(CASE WHEN pid % 50 = 0 THEN 1 ELSE 0 END)::BIGINT AS queries, round(avg(n), 6) AS mean_points, sum(b)::BIGINT AS wkt_bytes FROM (SELECT pid, count(*) AS n, 12 + sum(length(x::VARCHAR) + length(y::VARCHAR) + 3) + length(max(CASE WHEN idx = i0 THEN x::VARCHAR || y::VARCHAR END)) + 1 AS b FROM (SELECT *, min(idx) OVER (PARTITION BY pid) AS i0 FROM {name}__c) GROUP BY pid)")
    return O.text(ctes, " UNION ALL ".join(rows))


def frame_box(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in PROFILED:
        row = layers.build(spark, sf_dir, name).agg(*(f(f"box.{a}").alias(a) for a, f in (("xmin", F.min), ("xmax", F.max), ("ymin", F.min), ("ymax", F.max)))).select(F.lit(name).alias("layer"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _frame_sql() -> str:
    ctes: O.Cte = []
    for name in PROFILED:
        ctes += O.prepared(name, f"{name}__")
    return O.text(ctes, " UNION ALL ".join(f"SELECT '{n}' AS layer, xmin, xmax, ymin, ymax FROM {n}__frame" for n in PROFILED))


def centroids(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return layers.build(spark, sf_dir, name).select("pid", "cx", "cy", "area2", "box.*")


def hulls(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    ring = F.col("ring")
    return layers.rings(spark, sf_dir, name, "hull").where(G.area2(ring) != 0).select("pid", F.size(ring).cast("bigint").alias("points"), G.area2(ring).alias("area2"))


def _hull_sql(name: str) -> str:
    # A directed pair of points is an edge if no point lies to its right and none beyond its ends on its line.
    ctes = O.vertices(name)
    return O.text(ctes, """SELECT pid, count(*) AS points, sum(ax * by_ - bx * ay)::BIGINT AS area2 FROM (
      SELECT a.pid, a.x AS ax, a.y AS ay, b.x AS bx, b.y AS by_ FROM v a JOIN v b ON a.pid = b.pid AND (a.x <> b.x OR a.y <> b.y)
      WHERE NOT EXISTS (SELECT 1 FROM v c WHERE c.pid = a.pid AND ((b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) < 0
        OR ((b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) = 0 AND (c.x - a.x) * (c.x - b.x) + (c.y - a.y) * (c.y - b.y) > 0))))
      GROUP BY pid HAVING sum(ax * by_ - bx * ay) <> 0""")


def samples_head(spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = layers.build(spark, sf_dir, "doc")
    return samples(spark, P.global_frame(poly), [0, 1, 16, 17], 1, 32).select("slot", "attempt", "px", "py")


# ---- hashing


def signatures(name: str, form: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    return first_hit(poly, P.global_frame(poly), slots_of(5 if form == "arrow" else 2), None if form == "arrow" else cap_of(name), form=form)


def _signature_sql(name: str, form: str) -> str:
    return O.text([*O.prepared(name), *O.hits(slots_of(5 if form == "arrow" else 2), cap_of(name), most=O.MOST if form == "arrow" else 0)], "SELECT pid, slot, h FROM h")


OPEN = ("cust", "cust_sized", "flag", "supp_sized", "doc")


def open_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slots that ``PLAIN_CAP`` attempts leave open, their shapes, and the slots open when none is the limit."""
    out = None
    for name in OPEN:
        poly = prepared(spark, sf_dir, name)
        frame = P.global_frame(poly)
        short = first_hit(poly, frame, slots_of(3), PLAIN_CAP).where("h IS NULL").agg(F.count(F.lit(1)).alias("open_slots"), F.countDistinct("pid").alias("shapes"))
        full = first_hit(poly, frame, slots_of(3), None).agg(F.coalesce(F.sum(F.col("h").isNull().cast("bigint")), F.lit(0)).alias("open_uncapped"))
        row = short.crossJoin(F.broadcast(full)).select(F.lit(name).alias("layer"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _open_sql() -> str:
    ctes: O.Cte = []
    rows = []
    for n in OPEN:
        ctes += [*O.prepared(n, f"{n}__"), *((f"{n}__smp" if k == "smp" else k, q.replace("JOIN smp b", f"JOIN {n}__smp b")) for k, q in O.hits(slots_of(3), PLAIN_CAP, f"{n}__", f"{n}__frame"))]
        rows.append(f"SELECT '{n}' AS layer, (SELECT count(*) FROM {n}__open) AS open_slots, (SELECT count(DISTINCT pid) FROM {n}__open) AS shapes, (SELECT count(*) FROM {n}__h WHERE h IS NULL) AS open_uncapped")
    return O.text(ctes, " UNION ALL ".join(rows))


def buckets(name: str, m: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    index = ix.bucket_index(signature(poly, P.global_frame(poly), m, 2), m, 2)
    return index.groupBy("band", "code").agg(F.count(F.lit(1)).alias("cnt"))


def _coded(name: str, m: int, bands: int = 2) -> O.Cte:
    return [*O.prepared(name), *O.hits(slots_of(m, bands), cap_of(name)), *O.codes(m, bands)]


def bucket_stats(name: str, m: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    return ix.bucket_stats(ix.bucket_index(signature(poly, P.global_frame(poly), m, 2), m, 2))


def _bucket_stats_sql(name: str, m: int) -> str:
    return O.text([*_coded(name, m), ("sz", "SELECT band, code, count(*) AS cnt FROM code GROUP BY band, code")], "SELECT band, count(*) AS buckets, sum(cnt)::BIGINT AS entries, max(cnt) AS largest, round(max(cnt) / sum(cnt), 6) AS largest_share FROM sz GROUP BY band")


def candidate_pairs(name: str, m: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    return S.candidate_pairs(poly, query_set(poly), P.global_frame(poly), m, 2)


# ---- searches


def knn_exact(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    return S.knn_exact(poly, query_set(poly), 10)


def _exact_sql(name: str, k: int = 10) -> str:
    return O.text([*O.prepared(name), *O.all_pairs(), *O.distance(), *O.ranked(k)], "SELECT qid, rank, pid, jd FROM knn")


def knn_approx(name: str, m: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(spark, sf_dir, name, m, 2, 10)


def _approx_sql(name: str, m: int, bands: int = 2, k: int = 10) -> str:
    return O.text([*_coded(name, m, bands), *O.pairs_of_codes(), *O.distance(), *O.ranked(k)], "SELECT qid, rank, pid, jd FROM knn")


def k3_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three nearest documents of document 0."""
    poly = prepared(spark, sf_dir, "doc")
    return S.knn_approx(poly, poly.where("pid = 0"), P.global_frame(poly), 3, 2, 2)


def nearest_sets(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    return S.nearest_set(S.knn_exact(poly, query_set(poly), 1, ties=True))


def range_pairs(name: str, most: float, spark: SparkSession, sf_dir: str) -> DataFrame:
    poly = prepared(spark, sf_dir, name)
    return S.range_search(poly, query_set(poly), most)


#: The accuracy grid: layer -> lengths.
GRID = {"cust": (1, 3, 5), "cust_sized": (1, 3, 5), "cust_bal": (1, 3), "emb": (1, 2, 3), "emb_sized": (1, 2, 3), "flag": (1, 3), "flag_sized": (1, 3), "supp": (1, 2, 3), "supp_sized": (1, 2, 3), "doc": (1, 2, 3, 4, 5), "doc_sized": (1, 2, 3, 4, 5), "user": (1, 3)}


def _evaluated(spark: SparkSession, sf_dir: str, name: str, lengths: tuple[int, ...], bands: int = 2) -> dict:
    """Recall and pruning frames of each length, with one brute-force pass for all."""
    poly = prepared(spark, sf_dir, name)
    q = settle(query_set(poly))
    frame, n, nq = P.global_frame(poly), poly.count(), q.count()
    found = settle(S.nearest(poly, q, max(KS), True, frame, lengths, bands))
    lists = found.where("qid IS NOT NULL")
    exact = settle(S.top_k(lists.where("m = 0"), max(KS)))
    out = {}
    for m in lengths:
        approx = S.top_k(lists.where(F.col("m") == m), max(KS))
        out[(name, m)] = (M.recall_at_k(approx, exact, KS), M.pruned(found.where((F.col("m") == m) & F.col("qid").isNull()), n, nq))
    return out


def recall(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(layer, m, k, recall, cands, pruned_pct) of the grid's lengths."""
    return M.tradeoff(_evaluated(spark, sf_dir, name, GRID[name]))


def _evaluation(name: str, lengths: tuple[int, ...], bands: int = 2, p: str = "") -> tuple[O.Cte, list[str]]:
    ctes = [*O.prepared(name, p), *O.hits(slots_of(max(lengths), bands), cap_of(name), p, f"{p}frame"), *O.all_pairs(p, p, f"{p}pair"), *O.distance(f"{p}pair", p, p, f"{p}jd"), *O.ranked(max(KS), f"{p}jd", f"{p}knn")]
    parts = []
    for m in lengths:
        t = f"{p}m{m}"
        ctes += [(f"{t}code", O.codes(m, bands, p)[0][1]), (f"{t}pair", O.pairs_of_codes(t, t, f"{t}pair")[0][1]), (f"{t}knn", f"SELECT qid, pid, row_number() OVER (PARTITION BY qid ORDER BY jd, pid) AS got FROM {t}pair JOIN {p}jd USING (qid, pid)")]
        ctes.append((f"{t}r", f"SELECT k, round(avg(r), 6) AS recall FROM (SELECT e.qid, k, sum(CASE WHEN got <= k THEN 1 ELSE 0 END) / count(*) AS r FROM {p}knn e LEFT JOIN {t}knn a USING (qid, pid), (SELECT unnest({KS}) AS k) WHERE e.rank <= k GROUP BY e.qid, k) GROUP BY k"))
        parts.append(f"SELECT '{name}' AS layer, {m} AS m, k::INT AS k, recall, (SELECT count(*) FROM {t}pair) AS cands, round(100.0::DOUBLE * (1 - (SELECT count(*) FROM {t}pair) / ((SELECT count(*) FROM {p}s WHERE pid % 50 = 0) * ((SELECT count(*) FROM {p}s) - 1))::DOUBLE), 6) AS pruned_pct FROM {t}r")
    return ctes, parts


def _recall_sql(name: str) -> str:
    ctes, parts = _evaluation(name, GRID[name])
    return O.text(ctes, " UNION ALL ".join(parts))


def length_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths 1 to 5: points drawn for all hashes, candidates, recall at 10. Operation counts stand for seconds."""
    name = "cust_sized"
    poly = prepared(spark, sf_dir, name)
    frame = P.global_frame(poly)
    runs = _evaluated(spark, sf_dir, name, (1, 2, 3, 4, 5))
    out = None
    for m in range(1, 6):
        cost = attempt_costs(poly, frame, slots_of(m)).agg(F.sum("attempts").alias("attempts"))
        r, p = runs[(name, m)]
        row = r.where("k = 10").crossJoin(F.broadcast(p)).crossJoin(F.broadcast(cost)).select(F.lit(m).alias("m"), "attempts", "cands", "recall")
        out = row if out is None else out.unionByName(row)
    return out


def _sweep_sql() -> str:
    ctes, parts = _evaluation("cust_sized", (1, 2, 3, 4, 5))
    ctes.append(("t", " UNION ALL ".join(parts)))
    return O.text(ctes, f"SELECT m, (SELECT sum(h)::BIGINT FROM h WHERE slot % 16 < m) AS attempts, cands, recall FROM t WHERE k = 10")


def bands_compared(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One band against two, for lengths 1 and 3."""
    out = None
    for bands in (1, 2):
        t = M.tradeoff(_evaluated(spark, sf_dir, "cust_sized", (1, 3), bands)).withColumn("bands", F.lit(bands))
        out = t if out is None else out.unionByName(t)
    return out


def _bands_sql() -> str:
    ctes, rows = [], []
    for bands in (1, 2):
        c, parts = _evaluation("cust_sized", (1, 3), bands, f"b{bands}_")
        if bands == 2:
            c = [x for x in c if x[0] != "smp"]
        else:
            c = [(n, q if n != "smp" else O.drawn(slots_of(3, 2), SIZED_CAP, "b1_frame")[0][1]) for n, q in c]
            c = [(n, q if n != "b1_near" else q + " WHERE b.slot < 16") for n, q in c]
        ctes += c
        rows += [f"SELECT *, {bands} AS bands FROM ({p})" for p in parts]
    return O.text(ctes, " UNION ALL ".join(rows))


def tuned(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index for recall 0.9: length and bands from predicted recall, then measured against brute force.

    The prediction reads quantiles of the query set's ten nearest, and the distances of
    ``SPREAD_QUERIES`` queries to ``SPREAD_SHAPES`` shapes, the first by hash; the index
    holds every shape, and its recall is that of all queries.
    """
    from shapesig.plans import planner

    poly = prepared(spark, sf_dir, name)
    q = settle(query_set(poly))
    exact = settle(S.knn_exact(poly, q, 10))
    some, others = (x.orderBy(F.xxhash64("pid"), "pid").limit(most) for x, most in ((q, SPREAD_QUERIES), (poly, SPREAD_SHAPES)))
    m, bands = planner.tune_from_distances(exact, S.knn_exact(settle(others), settle(some), None, most=1.0), 0.95)
    frame, n, nq = P.global_frame(poly), poly.count(), q.count()
    while True:
        found = settle(S.nearest(poly, q, 10, False, frame, (m,), bands))
        r = settle(M.recall_at_k(S.top_k(found.where("qid IS NOT NULL"), 10), exact, [10]))
        # All shapes share one set of draws, so a measured recall can fall short of the predicted one: add bands.
        if bands >= MOST_BANDS or r.first()["recall"] >= TUNED_RECALL:
            break
        bands *= 2
    return r.crossJoin(F.broadcast(M.pruned(found.where("qid IS NULL"), n, nq))).select(F.lit(name).alias("layer"), F.lit(m).alias("m"), F.lit(bands).alias("bands"), "recall", "cands", "pruned_pct")


TUNED_RECALL, MOST_BANDS = 0.9, 256
SPREAD_QUERIES, SPREAD_SHAPES = 100, 2000


# ---- the two laws


def equal_slots(name: str, slots: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    """By tenth of similarity: mean similarity and mean share of equal slots, over all query pairs."""
    poly = prepared(spark, sf_dir, name)
    q = query_set(poly)
    frame = P.global_frame(poly)
    return S.similarity_tenths(poly, q, frame, list(range(slots)))


def _equal_slots_sql(name: str, slots: int) -> str:
    ctes = [*O.prepared(name), *O.hits(list(range(slots)), cap_of(name)), *O.all_pairs(), *O.distance()]
    ctes.append(("sh", "SELECT a.pid AS qid, b.pid, avg(CASE WHEN a.h = b.h THEN 1.0::DOUBLE ELSE 0.0 END) AS share FROM h a JOIN h b USING (slot) WHERE a.pid % 50 = 0 AND a.pid <> b.pid AND a.h IS NOT NULL AND b.h IS NOT NULL GROUP BY a.pid, b.pid"))
    return O.text(ctes, "SELECT least(floor(round((1 - jd) * 10, 5)), 9)::INT AS tenth, count(*) AS pairs, round(avg(1 - jd), 6) AS mean_j, round(avg(share), 6) AS mean_share FROM jd JOIN sh USING (qid, pid) GROUP BY 1")


def box_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centred boxes: the closed-form similarity against the share of equal slots, for all query pairs."""
    poly = prepared(spark, sf_dir, "box_part")
    hits = settle(first_hit(poly, P.global_frame(poly), list(range(64)), None))
    share = M.equal_share(hits.where(F.col("pid") % O.QUERY_STEP == 0), hits).where("qid <> pid")
    s = poly.select("pid", F.col("box.xmax").alias("hx"), F.col("box.ymax").alias("hy"))
    met = share.join(s, "pid").join(s.select(F.col("pid").alias("qid"), F.col("hx").alias("gx"), F.col("hy").alias("gy")), "qid")
    shared = F.least("hx", "gx") * F.least("hy", "gy")
    j = shared / (F.col("hx") * F.col("hy") + F.col("gx") * F.col("gy") - shared)
    return met.withColumn("j", j).groupBy(F.least(F.floor(F.round(F.col("j") * 10, 5)), F.lit(9)).cast("int").alias("tenth")).agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg("j"), 6).alias("mean_j"), F.round(F.avg("share"), 6).alias("mean_share"))


def _box_shares_sql() -> str:
    ctes = [*O.prepared("box_part"), *O.hits(list(range(64)), PLAIN_CAP)]
    ctes.append(("sh", "SELECT a.pid AS qid, b.pid, avg(CASE WHEN a.h = b.h THEN 1.0::DOUBLE ELSE 0.0 END) AS share FROM h a JOIN h b USING (slot) WHERE a.pid % 50 = 0 AND a.pid <> b.pid AND a.h IS NOT NULL AND b.h IS NOT NULL GROUP BY a.pid, b.pid"))
    ctes.append(("jj", "SELECT share, least(a.xmax, b.xmax) * least(a.ymax, b.ymax) / (a.xmax * a.ymax + b.xmax * b.ymax - least(a.xmax, b.xmax) * least(a.ymax, b.ymax))::DOUBLE AS j FROM sh JOIN s a ON a.pid = sh.pid JOIN s b ON b.pid = sh.qid"))
    return O.text(ctes, "SELECT least(floor(round(j * 10, 5)), 9)::INT AS tenth, count(*) AS pairs, round(avg(j), 6) AS mean_j, round(avg(share), 6) AS mean_share FROM jj GROUP BY 1")


def attempt_law(name: str, slots: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per shape: sparsity, mean and variance of the first-hit values, and what the geometric law expects."""
    poly = prepared(spark, sf_dir, name)
    frame = P.global_frame(poly)
    stats = M.attempt_stats(first_hit(poly, frame, list(range(slots)), None))
    s = F.col("sparsity")
    met = P.with_sparsity(poly, frame).join(stats, "pid")
    return met.select("pid", F.round(s, 9).alias("sparsity"), F.round("mean_h", 6).alias("mean_h"), F.round(1 / s, 6).alias("expected_mean"), F.round("var_h", 6).alias("var_h"), F.round((1 - s) / (s * s), 6).alias("expected_var"))


def _attempt_law_sql(name: str, slots: int) -> str:
    ctes = [*O.prepared(name), *O.hits(list(range(slots)), 1024), ("sp", "SELECT pid, area2 / (2.0::DOUBLE * (f.xmax - f.xmin) * (f.ymax - f.ymin)) AS sp FROM s, frame f")]
    return O.text(ctes, "SELECT pid, round(sp, 9) AS sparsity, round(avg(h), 6) AS mean_h, round(1 / sp, 6) AS expected_mean, round(var_samp(h), 6) AS var_h, round((1 - sp) / (sp * sp), 6) AS expected_var FROM h JOIN sp USING (pid) WHERE h IS NOT NULL GROUP BY pid, sp")


def precheck(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inside tests with and without the box check, on the rings with most vertices."""
    poly = prepared(spark, sf_dir, "supp_sized")
    frame = P.global_frame(poly)
    sums = [attempt_costs(poly, frame, slots_of(3), precheck=on).agg(F.sum("attempts").alias("attempts"), F.sum("tests").alias("tests")).select(F.lit(on).alias("box_check"), "*") for on in (True, False)]
    return sums[0].unionByName(sums[1])


def _precheck_sql() -> str:
    ctes = [*O.prepared("supp_sized"), *O.hits(slots_of(3), SIZED_CAP), ("a", "SELECT pid, slot, h FROM h"), ("tested", "SELECT * FROM near UNION ALL SELECT * FROM near2")]
    return O.text(ctes, "SELECT true AS box_check, (SELECT sum(h)::BIGINT FROM a) AS attempts, (SELECT count(*) FROM tested JOIN a USING (pid, slot) WHERE attempt <= a.h) AS tests UNION ALL SELECT false, (SELECT sum(h)::BIGINT FROM a), (SELECT sum(h)::BIGINT FROM a)")


def sparsity(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in ("cust", "cust_sized", "emb", "doc", "box_part"):
        poly = prepared(spark, sf_dir, name)
        row = M.sparsity(poly, P.global_frame(poly)).select(F.lit(name).alias("layer"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _sparsity_sql() -> str:
    ctes: O.Cte = []
    rows = []
    for n in ("cust", "cust_sized", "emb", "doc", "box_part"):
        ctes += [*O.prepared(n, f"{n}__"), (f"{n}__sp", f"SELECT area2 / (2.0::DOUBLE * (f.xmax - f.xmin) * (f.ymax - f.ymin)) AS sp FROM {n}__s, {n}__frame f")]
        rows.append(f"SELECT '{n}' AS layer, count(*) AS shapes, round(avg(sp), 9) AS mean_s, round(min(sp), 9) AS min_s, round(max(sp), 9) AS max_s, round(avg(1 / sp), 6) AS mean_attempts FROM {n}__sp")
    return O.text(ctes, " UNION ALL ".join(rows))


def size_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in ("cust", "flag", "supp", "emb"):
        row = M.size_ratio(layers.build(spark, sf_dir, name), 6).select(F.lit(name).alias("layer"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def bounds_lossless(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows in which brute force with and without bounds differ."""
    poly = prepared(spark, sf_dir, "cust_sized")
    q = query_set(poly)
    a, b = settle(S.knn_exact(poly, q, 10, bounds=False)), settle(S.knn_exact(poly, q, 10))
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("differing"))


# ---- uses around the searches


def near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents whose letter shapes lie within 0.05: each with its class and its links to other shapes' classes."""
    poly = prepared(spark, sf_dir, "doc")
    shapes, members = S.same_shapes(poly)
    shapes = settle(P.center(shapes, "none"))
    links = settle(S.self_join(shapes, 0.05))
    degree = links.select(F.explode(F.array("a", "b")).alias("cls")).groupBy("cls").agg(F.count(F.lit(1)).alias("n_links"))
    return members.join(degree, "cls", "left").select("pid", "cls", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"))


def _near_duplicates_sql() -> str:
    ctes = [*O.prepared("doc"), ("sig", "SELECT pid, string_agg(x || ' ' || y, ',' ORDER BY idx) AS ring FROM c GROUP BY pid"), ("cls", "SELECT pid, min(pid) OVER (PARTITION BY ring) AS cls FROM sig")]
    ctes.append(("pair", "SELECT a.cls AS qid, b.cls AS pid FROM (SELECT DISTINCT cls FROM cls) a JOIN (SELECT DISTINCT cls FROM cls) b ON a.cls < b.cls JOIN s sa ON sa.pid = a.cls JOIN s sb ON sb.pid = b.cls WHERE least(sa.area2, sb.area2) >= 0.949 * greatest(sa.area2, sb.area2)"))
    ctes += [*O.distance(), ("deg", "SELECT cls, count(*) AS n FROM (SELECT qid AS cls FROM jd WHERE jd <= 0.05 UNION ALL SELECT pid FROM jd WHERE jd <= 0.05) GROUP BY cls")]
    return O.text(ctes, "SELECT pid, cls, coalesce(n, 0)::BIGINT AS n_links FROM cls LEFT JOIN deg USING (cls)")


def filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Search among the documents labelled good: the label joins below the probe."""
    good = table(spark, sf_dir, "labels").where("quality = 1").select(F.col("doc_id").alias("pid")).distinct()
    poly = prepared(spark, sf_dir, "doc")
    frame = P.global_frame(poly)
    return S.knn_approx(poly.join(good, "pid", "left_semi"), query_set(poly), frame, 10, 2, 2)


def _filtered_sql() -> str:
    return O.text([*_coded("doc", 2), ("good", "SELECT DISTINCT doc_id AS pid FROM labels WHERE quality = 1"), ("pair", "SELECT DISTINCT q.pid AS qid, c.pid FROM code q JOIN code c USING (band, code) JOIN good g ON g.pid = c.pid WHERE q.pid % 50 = 0 AND q.pid <> c.pid"), *O.distance(), *O.ranked(10)], "SELECT qid, rank, pid, jd FROM knn")


def nation_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean distance to the nearest shape, by nation within region, with totals."""
    poly = prepared(spark, sf_dir, "cust_sized")
    near = S.knn_exact(poly, query_set(poly), 1)
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    n = F.broadcast(table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name"))  # 25 rows
    met = near.join(c, F.col("qid") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    return met.rollup("r_name", "n_name").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("queries"), F.round(F.avg("jd"), 6).alias("mean_jd"))


def _nation_sql() -> str:
    return O.text([*O.prepared("cust_sized"), *O.all_pairs(), *O.distance(), *O.ranked(1)], "SELECT r_name, n_name, grouping(r_name, n_name)::INT AS level, count(*) AS queries, round(avg(jd), 6) AS mean_jd FROM knn JOIN customer ON c_custkey = qid JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")


def cross_layer(source: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes of another layer as queries on the documents, hashed in the frame of both."""
    poly, other = prepared(spark, sf_dir, "doc"), prepared(spark, sf_dir, source)
    return S.knn_approx(poly, query_set(other), P.global_frame(poly, other), 5, 2, 2, exclude_self=False)


def _cross_sql(source: str) -> str:
    both = ("both_frame", "SELECT min(xmin) AS xmin, max(xmax) AS xmax, min(ymin) AS ymin, max(ymax) AS ymax FROM (SELECT * FROM frame UNION ALL SELECT * FROM q_frame)")
    ctes = [*O.prepared("doc"), *O.prepared(source, "q_"), both, *O.hits(slots_of(2), PLAIN_CAP, "", "both_frame"), *O.hits(slots_of(2), PLAIN_CAP, "q_", "both_frame", smp=False), *O.codes(2, 2), *O.codes(2, 2, "q_"), *O.pairs_of_codes("", "q_", distinct_self=False), *O.distance("pair", "", "q_"), *O.ranked(5)]
    return O.text(ctes, "SELECT qid, rank, pid, jd FROM knn")


def wkt_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes, and those that text or binary form does not give back."""
    p = layers.build(spark, sf_dir, "cust").select("pid", "ring")
    back = wkt.parse(wkt.format_rings(p), "wkt").select("pid", F.col("ring").alias("again"))
    binary = wkt.from_wkb(wkt.to_wkb(p)).select("pid", F.col("ring").alias("twice"))
    met = p.join(back, "pid", "left").join(binary, "pid", "left")
    return met.agg(F.count(F.lit(1)).alias("shapes"), F.sum(F.when(F.col("ring").eqNullSafe(F.col("again")) & F.col("ring").eqNullSafe(F.col("twice")), 0).otherwise(1)).alias("differing"))


def window_rings(spark: SparkSession, sf_dir: str) -> DataFrame:
    from shapesig.streaming.stream import weekly_rings_batch

    return weekly_rings_batch(table(spark, sf_dir, "events"), whole_seconds=True).select("pid", "area2", F.size("ring").cast("bigint").alias("points"), "user_id", "week")


def _window_sql() -> str:
    point = "SELECT DISTINCT user_id * 100000 + epoch(ts)::BIGINT // 604800 AS pid, (8 * (hour(ts) * 60 + minute(ts)))::BIGINT AS x, (2 * floor(least(greatest(value, 0.0), 500.0) * 10))::BIGINT AS y FROM events"
    ctes = [("pt", point), *[(n, q) for n, q in O.prepared("user") if n != "pt"]]
    return O.text(ctes, "SELECT pid, area2, n AS points, pid // 100000 AS user_id, pid % 100000 AS week FROM s")


def stream_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weekly rings of the event stream, each with its nearest all-time user shapes."""
    from shapesig.streaming.stream import weekly_rings_batch

    base = prepared(spark, sf_dir, "user")
    week = settle(weekly_rings_batch(table(spark, sf_dir, "events"), whole_seconds=True).select("pid", "ring", "area2", "cx", "cy", "box"))
    asked = week.where(F.floor(F.col("pid") / 100_000) % O.QUERY_STEP == 0)  # by user
    return S.knn_approx(base, asked, P.global_frame(base, week), 3, 1, 2, exclude_self=False)


def _stream_sql() -> str:
    weeks = [(f"q_{n}", q) for n, q in [("pt", "SELECT DISTINCT user_id * 100000 + epoch(ts)::BIGINT // 604800 AS pid, (8 * (hour(ts) * 60 + minute(ts)))::BIGINT AS x, (2 * floor(least(greatest(value, 0.0), 500.0) * 10))::BIGINT AS y FROM events")]]
    weeks += [x for x in O.prepared("user", "q_") if x[0] != "q_pt"]
    both = ("both_frame", "SELECT min(xmin) AS xmin, max(xmax) AS xmax, min(ymin) AS ymin, max(ymax) AS ymax FROM (SELECT * FROM frame UNION ALL SELECT * FROM q_frame)")
    ctes = [*O.prepared("user"), *weeks, both, *O.hits(slots_of(1), PLAIN_CAP, "", "both_frame"), *O.hits(slots_of(1), PLAIN_CAP, "q_", "both_frame", smp=False), *O.codes(1, 2), *O.codes(1, 2, "q_"), *O.pairs_of_codes("", "q_", queries=f"(q.pid // 100000) % {O.QUERY_STEP} = 0", distinct_self=False), *O.distance("pair", "", "q_"), *O.ranked(3)]
    return O.text(ctes, "SELECT qid, rank, pid, jd FROM knn")


def similar_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with the cluster that links of distance 0.05 or less put them in."""
    shapes, members = S.same_shapes(prepared(spark, sf_dir, "doc"))
    links = settle(S.self_join(settle(P.center(shapes, "none")), 0.05))
    found = clusters(links.select("a", "b")).withColumnRenamed("node", "cls")
    return members.join(found, "cls", "left").select("pid", F.coalesce("cluster", "cls").alias("cluster"))


def _clusters_sql() -> str:
    near = _near_duplicates_sql().split("\nSELECT pid, cls")[0].rsplit(",\ndeg AS", 1)[0].replace("WITH ", "WITH RECURSIVE ", 1)
    return near + """,
link AS MATERIALIZED (SELECT qid AS a, pid AS b FROM jd WHERE jd <= 0.05 UNION SELECT pid, qid FROM jd WHERE jd <= 0.05),
reach(a, b) AS (SELECT a, b FROM link UNION SELECT r.a, l.b FROM reach r JOIN link l ON l.a = r.b)
SELECT c.pid, least(c.cls, coalesce(min(r.b), c.cls)) AS cluster FROM cls c LEFT JOIN reach r ON r.a = c.cls GROUP BY c.pid, c.cls"""


def mean_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By length: mean distance of the returned neighbours, and of the true ones (length 0)."""
    poly = prepared(spark, sf_dir, "doc_sized")
    found = settle(S.nearest(poly, query_set(poly), max(KS), True, P.global_frame(poly), GRID["doc_sized"], 2).where("qid IS NOT NULL"))
    out = None
    for m in (0, *GRID["doc_sized"]):
        row = M.mean_distance_at_k(S.top_k(found.where(F.col("m") == m), max(KS)), KS).select(F.lit(m).alias("m"), "k", "mean_jd")
        out = row if out is None else out.unionByName(row)
    return out


def _mean_distances_sql() -> str:
    ctes, _ = _evaluation("doc_sized", GRID["doc_sized"])
    rows = ["SELECT 0 AS m, rank AS r, jd FROM knn"] + [f"SELECT {m}, got, jd FROM m{m}knn JOIN jd USING (qid, pid)" for m in GRID["doc_sized"]]
    return O.text(ctes, f"SELECT m, k::INT AS k, round(avg(jd), 6) AS mean_jd FROM ({' UNION ALL '.join(rows)}), (SELECT unnest({KS}) AS k) WHERE r <= k GROUP BY m, k")


def estimated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """True neighbours with their similarity and its estimate from long signatures."""
    poly = prepared(spark, sf_dir, "doc")
    near = settle(S.knn_exact(poly, query_set(poly), 10))
    held = poly.join(near.select(F.explode(F.array("qid", "pid")).alias("pid")).distinct(), "pid", "left_semi")
    sig = settle(signature(held, P.global_frame(poly), 16, 4))  # slots 0 to 63
    met = near.join(sig.withColumnRenamed("sig", "s"), "pid").join(sig.select(F.col("pid").alias("qid"), F.col("sig").alias("t")), "qid")
    return met.select("qid", "pid", F.round(1 - F.col("jd"), 6).alias("j"), F.round(M.estimate_jaccard("s", "t"), 6).alias("estimate"))


def _estimated_sql() -> str:
    ctes = [*O.prepared("doc"), *O.hits(list(range(64)), PLAIN_CAP), *O.all_pairs(), *O.distance(), *O.ranked(10)]
    return O.text(ctes, "SELECT n.qid, n.pid, round(1 - n.jd, 6) AS j, round(avg(CASE WHEN a.h = b.h THEN 1.0::DOUBLE ELSE 0.0 END), 6) AS estimate FROM knn n JOIN h a ON a.pid = n.pid JOIN h b ON b.pid = n.qid AND b.slot = a.slot GROUP BY n.qid, n.pid, n.jd")


def monte_carlo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """True neighbours with their similarity and the share of sample points in both among those in either."""
    poly = prepared(spark, sf_dir, "doc")
    near = settle(S.knn_exact(poly, query_set(poly), 3))
    asked = poly.join(near.select(F.explode(F.array("qid", "pid")).alias("pid")).distinct(), "pid", "left_semi")
    held = settle(holding(asked, P.global_frame(poly), 0, POINTS))
    met = near.select("qid", "pid", "jd").join(held, "pid").join(held.select(F.col("pid").alias("qid"), F.col("attempts").alias("theirs")), "qid")
    n, nq, shared = F.size("attempts"), F.size("theirs"), F.size(F.array_intersect("attempts", "theirs"))
    # A pair is told only where a point lies in its shape.
    return met.where(n > 0).select("qid", "pid", F.round(1 - F.col("jd"), 6).alias("j"), F.round(shared / (n + nq - shared), 6).alias("estimate"))


POINTS = 512


def _monte_carlo_sql() -> str:
    ctes = [*O.prepared("doc"), *O.hits([0], POINTS, most=0), *O.all_pairs(), *O.distance(), *O.ranked(3)]
    return O.text(ctes, "SELECT n.qid, n.pid, round(1 - n.jd, 6) AS j, round(sum(CASE WHEN b.pid IS NOT NULL THEN 1 ELSE 0 END) / (count(*) + (SELECT count(*) FROM ins c WHERE c.pid = n.qid) - sum(CASE WHEN b.pid IS NOT NULL THEN 1 ELSE 0 END))::DOUBLE, 6) AS estimate FROM knn n JOIN ins a ON a.pid = n.pid LEFT JOIN ins b ON b.pid = n.qid AND b.attempt = a.attempt GROUP BY n.qid, n.pid, n.jd")


CURVE = {"cust_sized": (1, 3), "emb_sized": (1, 3), "doc_sized": (1, 3), "supp_sized": (1, 3)}


def curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall against pruning over layers and lengths, in one table."""
    runs: dict = {}
    for name, lengths in CURVE.items():
        runs |= _evaluated(spark, sf_dir, name, lengths)
    return M.tradeoff(runs)


def _curve_sql() -> str:
    ctes, rows = [], []
    for name, lengths in CURVE.items():
        c, parts = _evaluation(name, lengths, 2, f"{name}__")
        ctes += [(f"{name}__smp" if n == "smp" else n, q.replace("JOIN smp b", f"JOIN {name}__smp b")) for n, q in c]
        rows += parts
    return O.text(ctes, " UNION ALL ".join(rows))


def probe_by(how: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """The filter step with the join named."""
    poly = prepared(spark, sf_dir, "doc")
    index = ix.bucket_index(signature(poly, P.global_frame(poly), 2), 2)
    return ix.candidates(index.where(F.col("pid") % O.QUERY_STEP == 0), index, how=how)


def salted_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bucket sizes summed in two steps, so that a hot bucket's rows are counted in sixteen tasks."""
    poly = prepared(spark, sf_dir, "doc")
    index = ix.bucket_index(signature(poly, P.global_frame(poly), 1), 1)
    part = index.groupBy("band", "code", F.pmod(F.xxhash64("pid"), F.lit(16)).alias("salt")).agg(F.count(F.lit(1)).alias("n"))
    return part.groupBy("band", "code").agg(F.sum("n").alias("cnt"))


# ---- registry


def _registry() -> dict[str, tuple[Query, str | None]]:
    r: dict[str, tuple[Query, str | None]] = {
        "w1_layer_profile": (layer_profile, _profile_sql()),
        "w2_frame_box": (frame_box, _frame_sql()),
        "w4_samples_head": (samples_head, O.text([*O.prepared("doc"), *O.drawn([0, 1, 16, 17], 32)], "SELECT slot, attempt, px, py FROM smp")),
        "m14_clusters": (similar_clusters, _clusters_sql()),
        "a17_mean_distance": (mean_distances, _mean_distances_sql()),
        "m11_estimated_jaccard": (estimated, _estimated_sql()),
        "g10_monte_carlo": (monte_carlo, _monte_carlo_sql()),
        "w14_curve": (curve, _curve_sql()),
        "ag11_salted_counts": (salted_counts, O.text(_coded("doc", 1), "SELECT band, code, count(*) AS cnt FROM code GROUP BY band, code")),
        "m6b_open_slots": (open_slots, _open_sql()),
        "w10_k3_example": (k3_example, O.text([*_coded("doc", 2), *O.pairs_of_codes(queries="q.pid = 0"), *O.distance(), *O.ranked(3)], "SELECT qid, rank, pid, jd FROM knn")),
        "w13_length_sweep": (length_sweep, _sweep_sql()),
        "w15_theorem1_boxes": (box_shares, _box_shares_sql()),
        "w18_bands_1_vs_2": (bands_compared, _bands_sql()),
        "w19_precheck_ablation": (precheck, _precheck_sql()),
        "w20_bounds_lossless": (bounds_lossless, "SELECT 0::BIGINT AS differing"),
        "w22_near_dup_docs": (near_duplicates, _near_duplicates_sql()),
        "w23_filtered_knn": (filtered, _filtered_sql()),
        "w24_nation_rollup": (nation_rollup, _nation_sql()),
        "w26_window_rings": (window_rings, _window_sql()),
        "w26_stream_probe": (stream_probe, _stream_sql()),
        "w27_wkt_roundtrip": (wkt_roundtrip, O.text(O.prepared("cust"), "SELECT count(*) AS shapes, 0::BIGINT AS differing FROM s")),
        "a12_sparsity": (sparsity, _sparsity_sql()),
        "a15_size_ratio": (size_ratio, _ratio_sql()),
    }
    for n in ("cust", "doc", "supp"):
        r[f"w3_centroids_{n}"] = (partial(centroids, n), O.text(O.prepared(n), "SELECT pid, cx, cy, area2, xmin, xmax, ymin, ymax FROM s"))
    for n in ("cust", "flag", "part"):
        r[f"g9_hull_{n}"] = (partial(hulls, n), _hull_sql(n))
    for n in ("cust", "flag", "supp", "emb", "doc", "user", "cust_sized", "doc_sized"):
        r[f"w5_sig_{n}"] = (partial(signatures, n, "arrow"), _signature_sql(n, "arrow"))
    for form in ("sql", "expr", "grid"):
        r[f"m5_first_hit_{form}"] = (partial(signatures, "doc", form), _signature_sql("doc", form))
    for m in (1, 2, 3, 5):
        for n in ("cust", "doc"):
            r[f"w6_buckets_{n}_m{m}"] = (partial(buckets, n, m), O.text(_coded(n, m), "SELECT band, code, count(*) AS cnt FROM code GROUP BY band, code"))
    r["a14_bucket_stats"] = (partial(bucket_stats, "doc", 1), _bucket_stats_sql("doc", 1))
    for n, m in (("cust", 1), ("cust", 3), ("flag", 3), ("emb", 2), ("supp", 2)):
        r[f"w7_cand_{n}_m{m}"] = (partial(candidate_pairs, n, m), O.text([*_coded(n, m), *O.pairs_of_codes()], "SELECT qid, pid FROM pair"))
    for n in ("cust", "flag", "supp", "emb", "doc", "user", "cust_sized", "box_acct", "part"):
        r[f"w8_knn_exact_{n}"] = (partial(knn_exact, n), _exact_sql(n))
    r["b1a_knn_bounded_flag_sized"] = (partial(knn_exact, "flag_sized"), _exact_sql("flag_sized"))
    for n, m in (("cust", 1), ("cust", 3), ("cust", 5), ("flag", 3), ("emb", 2), ("supp", 2), ("doc", 3), ("cust_sized", 3), ("doc_sized", 4), ("order", 3)):
        r[f"w9_knn_approx_{n}_m{m}"] = (partial(knn_approx, n, m), _approx_sql(n, m))
    for n in GRID:
        r[f"w11_w12_recall_pruning_{n}"] = (partial(recall, n), _recall_sql(n))
    for n, slots in (("cust", 24), ("emb", 24)):
        r[f"w16_theorem1_{n}"] = (partial(equal_slots, n, slots), _equal_slots_sql(n, slots))
    for n, slots in (("box_part", 16), ("doc", 16)):
        r[f"w17_theorem2_{n}"] = (partial(attempt_law, n, slots), _attempt_law_sql(n, slots))
    r["m10b_nearest_set"] = (partial(nearest_sets, "doc"), O.text([*O.prepared("doc"), *O.all_pairs(), *O.distance()], "SELECT qid, pid, jd FROM (SELECT *, rank() OVER (PARTITION BY qid ORDER BY jd) AS r FROM jd) WHERE r = 1"))
    r["m13_range_search"] = (partial(range_pairs, "doc", 0.1), O.text([*O.prepared("doc"), *O.all_pairs(), *O.distance()], "SELECT qid, pid, jd FROM jd WHERE jd <= 0.1"))
    for how in ("shuffle_hash", "merge"):
        r[f"j_probe_{how}"] = (partial(probe_by, how), O.text([*_coded("doc", 2), *O.pairs_of_codes()], "SELECT qid, pid FROM pair"))
    for n in ("bench", "page", "turn"):
        r[f"w25_cross_{n}"] = (partial(cross_layer, n), _cross_sql(n))
    for n in ("doc", "cust_sized", "emb"):
        r[f"tuned_index_{n}"] = (partial(tuned, n), None)
    return r


def _ratio_sql() -> str:
    ctes: O.Cte = []
    rows = []
    for n in ("cust", "flag", "supp", "emb"):
        ctes += O.prepared(n, f"{n}__")
        b = f"SELECT pid, 12 + sum(length(x::VARCHAR) + length(y::VARCHAR) + 3) + length(max(CASE WHEN idx = i0 THEN x::VARCHAR || y::VARCHAR END)) + 1 AS b FROM (SELECT *, min(idx) OVER (PARTITION BY pid) AS i0 FROM {n}__c) GROUP BY pid"
        rows.append(f"SELECT '{n}' AS layer, sum(b)::BIGINT AS ring_bytes, count(*) * 24 AS signature_bytes, round(sum(b) / (count(*) * 24), 6) AS ratio FROM ({b})")
    return O.text(ctes, " UNION ALL ".join(rows))


def queries() -> dict[str, Query]:
    return {k: q for k, (q, _) in _registry().items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in _registry().items() if s}
