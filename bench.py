"""Headline timings: one JSON line. BENCH_SF_DIR and BENCH_CPUS set the tables and the cores."""

from __future__ import annotations

import json
import os
import sys
import time

os.environ["PYTHONPATH"] = os.pathsep.join(filter(None, [os.path.dirname(os.path.abspath(__file__)), os.environ.get("PYTHONPATH", "")]))

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from shapesig import workloads as W  # noqa: E402
from shapesig.operators import measures as M  # noqa: E402
from shapesig.operators import prepare as P  # noqa: E402
from shapesig.operators import search as S  # noqa: E402
from shapesig.operators.signature import signature  # noqa: E402
from shapesig.session import settle  # noqa: E402

#: Layer and length of each published row's stand-in; small layers first.
ROWS = [("cust_sized", 1), ("cust_sized", 3), ("cust_sized", 5), ("emb_sized", 1), ("emb_sized", 2), ("emb_sized", 3), ("flag_sized", 1), ("flag_sized", 3), ("supp_sized", 1), ("supp_sized", 2), ("supp_sized", 3)]
#: Queries are the shapes whose id is divisible by this; all shapes of a layer are searched.
STEP = {"flag_sized": 1000, "emb_sized": 200, "cust_sized": 200}
QUERIES = ("w5_sig_cust", "w9_knn_approx_doc_m3", "w9_knn_approx_cust_m3", "w22_near_dup_docs", "w26_stream_probe")
#: Nothing new is begun after this many seconds; what was left out is listed.
SECONDS = float(os.environ.get("BENCH_SECONDS", "780"))


def layer(spark: SparkSession, sf_dir: str, name: str) -> dict:
    """A layer with its query set, frame and timed brute force."""
    poly = settle(W.prepared(spark, sf_dir, name))
    q = settle(poly.where(F.col("pid") % STEP.get(name, 50) == 0))
    frame = P.global_frame(poly)
    M.timed(signature(q, frame, 1, 2))  # workers and compiled code are warm
    t = time.perf_counter()
    exact = settle(S.knn_exact(poly, q, 100, bounds=False))
    return {"poly": poly, "q": q, "frame": frame, "exact_s": time.perf_counter() - t, "exact": exact, "n": poly.count(), "nq": q.count()}


def row(held: dict, m: int) -> dict:
    """Hashing, lookup with refinement, total, brute force, ratio, recall and pruning of one row."""
    poly, q, frame = held["poly"], held["q"], held["frame"]
    t = time.perf_counter()
    sig = settle(signature(poly, frame, m, 2))
    hash_s = time.perf_counter() - t
    index = W.ix.bucket_index(sig, m, 2)
    cand = W.ix.candidates(index.join(q.select("pid"), "pid", "left_semi"), index)
    t = time.perf_counter()
    found = settle(S.top_k(S.refine(cand, poly, q), 100))
    refine_s = time.perf_counter() - t
    recall = {r["k"]: r["recall"] for r in M.recall_at_k(found, held["exact"], W.KS).collect()}
    pruned = M.pruning(cand, held["n"], held["nq"]).first()["pruned_pct"]
    return {k: round(v, 3) for k, v in M.cost_report(hash_s, refine_s, held["exact_s"]).items()} | {"recall": recall, "pruned_pct": pruned, "shapes": held["n"], "queries": held["nq"]}


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    began = time.perf_counter()
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    times, table, left = {}, {}, []
    known = W.queries()
    held: dict = {}

    def late(what: str) -> bool:
        if time.perf_counter() - began > SECONDS:
            left.append(what)
            return True
        return False

    def told(what: str, value: object) -> None:
        print(f"{time.perf_counter() - began:7.1f} {what} {value}", file=sys.stderr, flush=True)

    for name, m in ROWS:
        if late(f"{name}_m{m}"):
            continue
        if held.get("name") != name:
            held = {"name": name} | layer(spark, sf_dir, name)
            times[f"{name}_exact"] = round(held["exact_s"], 3)
        table[f"{name}_m{m}"] = row(held, m)
        times[f"{name}_m{m}_total"] = table[f"{name}_m{m}"]["total_s"]
        told(f"{name}_m{m}", table[f"{name}_m{m}"])
    for name in QUERIES:
        if late(name):
            continue
        t = time.perf_counter()
        known[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - t, 3)
        told(name, times[name])
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "speed": table, "not_run": left, "sf": os.path.basename(sf_dir.rstrip("/"))}))


if __name__ == "__main__":
    sys.exit(main())
