"""Queries around the searches: joins, windows and aggregates that a user of neighbour lists runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shapesig import oracles as O
from shapesig import workloads as W
from shapesig.operators import index as ix
from shapesig.operators import prepare as P
from shapesig.operators import search as S
from shapesig.operators.signature import signature, slots_of
from shapesig.session import settle, table


def _lists(spark: SparkSession, sf_dir: str, name: str = "cust_sized", m: int = 3, k: int = 10) -> tuple[DataFrame, DataFrame]:
    """The exact and the approximate neighbours of the query set, from one pass."""
    poly = W.prepared(spark, sf_dir, name)
    found = settle(S.nearest(poly, W.query_set(poly), k, True, P.global_frame(poly), (m,), 2).where("qid IS NOT NULL"))
    exact, approx = (S.top_k(found.where(F.col("m") == kind), k) for kind in (0, m))
    return exact, approx


def _exact(spark: SparkSession, sf_dir: str, name: str = "cust_sized", k: int = 10) -> DataFrame:
    poly = W.prepared(spark, sf_dir, name)
    return settle(S.knn_exact(poly, W.query_set(poly), k))


def _lists_sql(name: str = "cust_sized", m: int = 3, k: int = 10) -> O.Cte:
    return [
        *O.prepared(name), *O.hits(slots_of(m), W.cap_of(name)), *O.codes(m, 2), *O.all_pairs(), *O.distance(), *O.ranked(k, name="exact_"),
        *O.pairs_of_codes(name="bp"), ("near_jd", "SELECT qid, pid, jd FROM jd JOIN bp USING (qid, pid)"), *O.ranked(k, "near_jd", "approx_"),
    ]


def unanswered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries without any candidate at length 5 (an anti-join), and their number of vertices."""
    poly = W.prepared(spark, sf_dir, "cust_sized")
    q = W.query_set(poly)
    cand = S.candidate_pairs(poly, q, P.global_frame(poly), 5, 2)
    return q.join(cand.select(F.col("qid").alias("pid")), "pid", "left_anti").select("pid", F.size("ring").cast("bigint").alias("points"))


def missed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """True neighbours that the buckets didn't give: EXCEPT, and INTERSECT for those they did."""
    exact, approx = _lists(spark, sf_dir)
    a, b = exact.select("qid", "pid"), approx.select("qid", "pid")
    return a.exceptAll(b).withColumn("found", F.lit(False)).unionByName(a.intersect(b).withColumn("found", F.lit(True)))


def compared(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both lists side by side (a full outer join): rank in each, 0 where it is not."""
    exact, approx = _lists(spark, sf_dir)
    a, b = exact.select("qid", "pid", F.col("rank").alias("exact_rank")), approx.select("qid", "pid", F.col("rank").alias("approx_rank"))
    return a.join(b, ["qid", "pid"], "full").select("qid", "pid", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("exact_rank", "approx_rank")))


def recall_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row a length, recall at each k as columns."""
    t = W.recall("doc_sized", spark, sf_dir)
    p = t.groupBy("m", "pruned_pct").pivot("k", W.KS).agg(F.first("recall"))
    return p.select("m", *(F.col(str(k)).alias(f"recall_{k}") for k in W.KS), "pruned_pct")


def windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Along each list: running mean distance, neighbours within 0.02 of this one, step from the last, quartile."""
    exact = _exact(spark, sf_dir)
    by = Window.partitionBy("qid").orderBy("rank")
    # Distances in millionths: a range frame over whole numbers is exact.
    near = Window.partitionBy("qid").orderBy("micro").rangeBetween(-20_000, 20_000)
    rows = exact.withColumn("micro", F.round(F.col("jd") * 1_000_000).cast("bigint"))
    return rows.select(
        "qid", "rank",
        F.round(F.avg("micro").over(by.rowsBetween(Window.unboundedPreceding, 0)), 3).alias("running"),
        F.count(F.lit(1)).over(near).alias("within"),
        (F.col("micro") - F.lag("micro", 1, 0).over(by)).alias("step"),
        F.ntile(4).over(by).alias("quartile"),
    )


def sparsity_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes of each twentieth of sparsity."""
    poly = W.prepared(spark, sf_dir, "cust_sized")
    s = P.with_sparsity(poly, P.global_frame(poly))
    return s.groupBy(F.width_bucket(F.round("sparsity", 9), F.lit(0.0), F.lit(1.0), F.lit(20)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("shapes"))


def hot_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Buckets with their rank by size in the band (dense), the five largest sizes."""
    poly = W.prepared(spark, sf_dir, "doc")
    index = ix.bucket_index(signature(poly, P.global_frame(poly), 1, 2), 1, 2)
    sizes = index.groupBy("band", "code").agg(F.count(F.lit(1)).alias("cnt"))
    w = Window.partitionBy("band").orderBy(F.desc("cnt"))
    return sizes.withColumn("place", F.dense_rank().over(w)).where("place <= 5")


def area_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each query the shapes whose area is within a twentieth of its own: a band join on area bins."""
    poly = W.prepared(spark, sf_dir, "cust_sized")
    width = float(-F_LOG)
    b = F.floor(F.log(F.col("area2").cast("double")) / width).cast("bigint")
    p = poly.select("pid", "area2", b.alias("bin"))
    q = W.query_set(poly).select(F.col("pid").alias("qid"), F.col("area2").alias("qarea2"), F.explode(F.array(b - 1, b, b + 1)).alias("bin"))
    close = (F.least("area2", "qarea2") * 20 >= F.greatest("area2", "qarea2") * 19) & (F.col("qid") != F.col("pid"))
    return p.join(F.broadcast(q), "bin").where(close).groupBy("qid").agg(F.count(F.lit(1)).alias("shapes"))


F_LOG = -0.0512932943875505  # natural logarithm of 0.95


def event_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The JSON property of events by type and kind of day, with subtotals."""
    e = table(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("bigint")
    day = F.when(F.dayofweek("ts").isin(1, 7), "weekend").otherwise("weekday")
    return e.select("event_type", day.alias("day"), k.alias("k")).cube("event_type", "day").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("events"), F.sum("k").alias("k_sum"), F.countDistinct("k").alias("k_kinds"))


def sides(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The boxes of shapes as one row a side (unpivot)."""
    box = W.prepared(spark, sf_dir, "cust").select("pid", "box.*")
    return box.unpivot("pid", ["xmin", "xmax", "ymin", "ymax"], "side", "value")


def page_of_shapes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The third page of twenty shapes by area: sort, offset and limit."""
    return W.prepared(spark, sf_dir, "cust").select("pid", "area2").orderBy(F.desc("area2"), "pid").offset(40).limit(20)


def event_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each user by type as a map, read back by key."""
    n = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    busy = F.map_filter("m", lambda k, v: v >= 3)
    return m.select("user_id", F.size("m").cast("bigint").alias("kinds"), F.size(busy).cast("bigint").alias("busy"), F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).cast("bigint").alias("clicks"), F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda a, v: a + v).alias("events"))


def list_places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places in each list of neighbours: relative ranks, and values ahead, first, last and third."""
    exact = _exact(spark, sf_dir)
    by = Window.partitionBy("qid").orderBy("rank")
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return exact.select(
        "qid", "rank",
        F.round(F.percent_rank().over(by), 6).alias("place"), F.round(F.cume_dist().over(by), 6).alias("up_to"),
        F.lead("pid", 1, -1).over(by).alias("ahead"), F.first("pid").over(whole).alias("nearest"), F.last("pid").over(whole).alias("farthest"), F.nth_value("pid", 3).over(whole).alias("third"),
    )


def common_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Areas that customers' and parts' shapes have in common, with repeats (INTERSECT ALL)."""
    a, b = (W.prepared(spark, sf_dir, n).select((F.floor(F.log2(F.col("area2").cast("double")) * 4)).cast("int").alias("grade")) for n in ("cust", "part"))
    return a.intersectAll(b).groupBy("grade").agg(F.count(F.lit(1)).alias("shapes"))


def queries() -> dict[str, W.Query]:
    return {"j10_unanswered": unanswered, "so_missed": missed, "j11_compared": compared, "ag9_recall_pivot": recall_pivot, "wn_neighbour_windows": windows, "ag6_sparsity_histogram": sparsity_histogram, "ag7_hot_codes": hot_codes, "j8_area_band": area_band, "fn7_event_props": event_props, "ag9_unpivot_sides": sides, "sl1_page_of_shapes": page_of_shapes, "fn5_event_maps": event_maps, "wn_list_places": list_places, "so_common_rows": common_rows}


def oracle_sql() -> dict[str, str]:
    lists = _lists_sql()
    five = [*O.prepared("cust_sized"), *O.hits(slots_of(5), W.SIZED_CAP), *O.codes(5, 2), *O.pairs_of_codes()]
    return {
        "j10_unanswered": O.text(five, "SELECT pid, n AS points FROM s WHERE pid % 50 = 0 AND pid NOT IN (SELECT qid FROM pair)"),
        "so_missed": O.text(lists, "SELECT e.qid, e.pid, a.pid IS NOT NULL AS found FROM exact_ e LEFT JOIN approx_ a USING (qid, pid)"),
        "j11_compared": O.text(lists, "SELECT qid, pid, coalesce(e.rank, 0) AS exact_rank, coalesce(a.rank, 0) AS approx_rank FROM exact_ e FULL JOIN approx_ a USING (qid, pid)"),
        "ag9_recall_pivot": "WITH t AS (" + W.oracle_sql()["w11_w12_recall_pruning_doc_sized"] + ") SELECT m, max(recall) FILTER (WHERE k = 10) AS recall_10, max(recall) FILTER (WHERE k = 50) AS recall_50, max(recall) FILTER (WHERE k = 100) AS recall_100, pruned_pct FROM t GROUP BY m, pruned_pct",
        "wn_neighbour_windows": O.text([*O.prepared("cust_sized"), *O.all_pairs(), *O.distance(), *O.ranked(10), ("u", "SELECT qid, rank, round(jd * 1000000)::BIGINT AS micro FROM knn")], "SELECT qid, rank, round(avg(micro) OVER (PARTITION BY qid ORDER BY rank ROWS UNBOUNDED PRECEDING), 3) AS running, count(*) OVER (PARTITION BY qid ORDER BY micro RANGE BETWEEN 20000 PRECEDING AND 20000 FOLLOWING) AS within, micro - lag(micro, 1, 0) OVER (PARTITION BY qid ORDER BY rank) AS step, (ntile(4) OVER (PARTITION BY qid ORDER BY rank))::INT AS quartile FROM u"),
        "ag6_sparsity_histogram": O.text([*O.prepared("cust_sized"), ("sp", "SELECT round(area2 / (2.0::DOUBLE * (f.xmax - f.xmin) * (f.ymax - f.ymin)), 9) AS sp FROM s, frame f")], "SELECT (CASE WHEN sp >= 1 THEN 21 ELSE floor(sp * 20) + 1 END)::INT AS bin, count(*) AS shapes FROM sp GROUP BY 1"),
        "ag7_hot_codes": O.text([*O.prepared("doc"), *O.hits(slots_of(1), W.PLAIN_CAP), *O.codes(1, 2), ("z", "SELECT band, code, count(*) AS cnt FROM code GROUP BY band, code")], "SELECT * FROM (SELECT band, code, cnt, (dense_rank() OVER (PARTITION BY band ORDER BY cnt DESC))::INT AS place FROM z) WHERE place <= 5"),
        "j8_area_band": O.text(O.prepared("cust_sized"), "SELECT q.pid AS qid, count(*) AS shapes FROM s q JOIN s p ON p.pid <> q.pid AND least(p.area2, q.area2) * 20 >= greatest(p.area2, q.area2) * 19 WHERE q.pid % 50 = 0 GROUP BY q.pid"),
        "ag9_unpivot_sides": O.text(O.prepared("cust"), " UNION ALL ".join(f"SELECT pid, '{c}' AS side, {c} AS value FROM s" for c in ("xmin", "xmax", "ymin", "ymax"))),
        "sl1_page_of_shapes": O.text(O.prepared("cust"), "SELECT pid, area2 FROM s ORDER BY area2 DESC, pid LIMIT 20 OFFSET 40"),
        "fn5_event_maps": "WITH n AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) SELECT user_id, count(*) AS kinds, sum(CASE WHEN n >= 3 THEN 1 ELSE 0 END)::BIGINT AS busy, sum(CASE WHEN event_type = 'click' THEN n ELSE 0 END)::BIGINT AS clicks, sum(n)::BIGINT AS events FROM n GROUP BY user_id",
        "wn_list_places": O.text([*O.prepared("cust_sized"), *O.all_pairs(), *O.distance(), *O.ranked(10)], "SELECT qid, rank, round(percent_rank() OVER w, 6) AS place, round(cume_dist() OVER w, 6) AS up_to, lead(pid, 1, -1) OVER w AS ahead, first_value(pid) OVER f AS nearest, last_value(pid) OVER f AS farthest, nth_value(pid, 3) OVER f AS third FROM knn WINDOW w AS (PARTITION BY qid ORDER BY rank), f AS (PARTITION BY qid ORDER BY rank ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"),
        "so_common_rows": O.text([*O.prepared("cust", "a__"), *O.prepared("part", "b__")], "SELECT grade, count(*) AS shapes FROM (SELECT floor(log2(area2::DOUBLE) * 4)::INT AS grade FROM a__s INTERSECT ALL SELECT floor(log2(area2::DOUBLE) * 4)::INT FROM b__s) GROUP BY grade"),
        "fn7_event_props": "SELECT event_type, day, grouping(event_type, day)::INT AS level, count(*) AS events, sum(k)::BIGINT AS k_sum, count(DISTINCT k) AS k_kinds FROM (SELECT event_type, CASE WHEN dayofweek(ts) IN (0, 6) THEN 'weekend' ELSE 'weekday' END AS day, (props ->> '$.k')::BIGINT AS k FROM events) GROUP BY CUBE (event_type, day)",
    }
