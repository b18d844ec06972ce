"""Mixing sources to target weights by Pareto order sampling.

A source's target is its weight's share of all words, at most ``most`` times its
own words, with the excess reshared by weight. A document is worth
``factor * grade(size)`` copies, ``most`` at most: longer texts are worth more
(``LEAN``), and the source's factor makes its documents' worth its target in words.
The whole copies are certain, and the fraction is the document's inclusion
probability p. Documents are ranked by random odds over inclusion odds,
``(u / (1 - u)) / (p / (1 - p))``, u from a keyed hash of the doc_id, and each stratum
(source and octave of the size) takes the first documents of that order up to its
fixed size in words. A correction pass then moves the source's remaining difference
by the order of its smaller documents.

Sizes are graded in ``GRADES`` steps an octave, so a source's factor is solved from a
few hundred sums. A stratum's cut is found on histograms of the order (two levels of
``BINS`` bins, which bound the rows that a window by stratum orders), so that only the
cells at the cut, a few documents each, are ranked by a window; a source of any size
is never gathered in a task.

Defined cases: null text has size 0; documents of size 0 take nothing; a null
source is a source of its own, the last; rows that repeat doc_id, source and text
count each and are drawn as one; other rows of one doc_id are documents each, with the
same u; extra columns pass through; an empty table gives no rows; a source without
words has target 0.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from shapesig.llm.common import SPACE, cut

WEIGHTS, MOST, SEED, BINS = (5.0, 2.0, 1.0), 3.0, 17, 4096
LEAN, GRADES = 0.25, 8


def word_count(text: Column) -> Column:
    """Words of a text: the places where one begins."""
    t = F.coalesce(text, F.lit(""))
    return F.length(F.regexp_replace(F.regexp_replace(t, r"[^\x20\x09-\x0D]+", "w"), f"{SPACE}+", "")).cast("long")


def targets(sizes: list[tuple[str | None, int]], weights: tuple[float, ...] = WEIGHTS, most: float = MOST) -> dict[str | None, float]:
    """Target words of each source (name, words): shares by weight, capped, the excess reshared until none is above."""
    order = sorted(sizes, key=lambda x: (x[0] is None, x[0] or ""))
    weight = {s: weights[i % len(weights)] for i, (s, _) in enumerate(order)}
    cap = {s: most * n for s, n in order}
    total, fixed = float(sum(n for _, n in order)), {}
    while True:
        free = [s for s, _ in order if s not in fixed]
        left = total - sum(fixed[s] for s, _ in order if s in fixed)
        share = math.fsum(weight[s] for s in free)
        now = {s: left * weight[s] / share for s in free}
        over = [s for s in free if now[s] > cap[s]]
        if not over:
            return fixed | now
        fixed |= {s: cap[s] for s in over}


def factor(words: dict[int, int], target: float, most: float = MOST, lean: float = LEAN) -> float:
    """The factor by which documents of the grades (grade -> words) are worth ``target`` words, none over ``most`` copies."""
    capped: set[int] = set()
    while True:
        free = {g: n for g, n in words.items() if g not in capped}
        left = target - most * sum(n for g, n in words.items() if g in capped)
        base = math.fsum(n * 2.0 ** (lean * g / GRADES) for g, n in sorted(free.items()))
        out = max(0.0, left) / base if base else most
        over = {g for g in free if out * 2.0 ** (lean * g / GRADES) > most}
        if not over:
            return out
        capped |= over


def grade(size: Column) -> Column:
    return F.floor(F.round(F.log2(size) * GRADES, 9)).cast("int")


def uniform(seed: int = SEED) -> Column:
    return (F.pmod(F.xxhash64(F.lit(seed), F.col("doc_id")), F.lit(1 << 52)).cast("double") + 0.5) / float(1 << 52)


def pareto_key(p: Column, seed: int = SEED) -> Column:
    """Random odds over inclusion odds, mapped to [0, 1) in the same order."""
    u = uniform(seed)
    odds, base = u / (1 - u), p / (1 - p)
    return odds / (odds + base)


def take_first(rows: DataFrame, by: list[str], goal: str) -> DataFrame:
    """Mark with ``picked`` the rows of each group that come first by ``key``, up to ``goal`` words (ends nearest to it).

    ``rows``: by..., key (in [0, 1)), size (positive), goal (the same in a group), doc_id, turn.
    """
    rows = rows.withColumn("bin", F.floor(F.col("key") * BINS).cast("int")).withColumn("sub", F.floor((F.col("key") * BINS - F.col("bin")) * BINS).cast("int"))
    rows = rows.withColumn("key2", F.col("key"))

    def cell(of: DataFrame, keys: list[str], level: str, base: str) -> DataFrame:
        """The cell of each group where the running words pass the goal, and the words before it."""
        sums = of.groupBy(*keys, level).agg(F.sum("size").alias("w"), F.first(goal).alias("g"), F.first(base).alias("b"))
        run = F.col("b") + F.sum("w").over(Window.partitionBy(*keys).orderBy(level))
        return sums.withColumn("end", run).where((F.col("end") > F.col("g")) & (F.col("end") - F.col("w") <= F.col("g"))).select(*(F.col(k).alias(f"c_{k}") for k in keys), F.col(level).alias(f"c_{level}"), (F.col("end") - F.col("w")).alias("before"))

    def same(keys: list[str]) -> Column:
        out = F.lit(True)
        for k in keys:
            out = out & F.col(k).eqNullSafe(F.col(f"c_{k}"))
        return out

    start = rows.withColumn("none", F.lit(0).cast("long"))
    c1 = cell(start, by, "bin", "none")
    one = rows.join(c1, same(by), "left").withColumn("side", F.when(F.col("c_bin").isNull() & (F.col(goal) > 0), -1).otherwise(F.signum(F.col("bin") - F.col("c_bin"))).cast("int")).drop(*(f"c_{k}" for k in by), "c_bin")
    at = one.where("side = 0")
    c2 = cell(at, by, "sub", "before").withColumnRenamed("before", "before2")
    two = at.join(c2, same(by), "left").withColumn("side", F.signum(F.col("sub") - F.col("c_sub")).cast("int")).drop(*(f"c_{k}" for k in by), "c_sub", "before").withColumnRenamed("before2", "before")
    end = F.col("before") + F.sum("size").over(Window.partitionBy(*by).orderBy("key", "doc_id", "turn").rowsBetween(Window.unboundedPreceding, 0))
    last = two.where("side = 0").withColumn("end", end).withColumn("side", F.when(F.col("end") - F.col("size") / 2.0 <= F.col(goal), -1).otherwise(1)).drop("end")
    every = one.where("side IS NULL OR side <> 0").unionByName(two.where("side IS NULL OR side <> 0")).unionByName(last)
    return every.withColumn("picked", F.coalesce(F.col("side") < 0, F.lit(False))).drop("side", "before", "bin", "sub", "key2")


def _units(docs: DataFrame, weights: tuple[float, ...], most: float, seed: int, lean: float) -> DataFrame:
    """(doc_id, source, text_, size, rows, source_size, target, copies) for each distinct row."""
    spark = docs.sparkSession
    text = F.struct(F.xxhash64("text").alias("h"), F.col("text").isNull().alias("none")).alias("text_")
    counted = docs.select("doc_id", "source", text, word_count(F.col("text")).alias("size")).groupBy("doc_id", "source", "text_", "size").agg(F.count(F.lit(1)).alias("rows"))
    # ``size`` is all the words of the unit's rows from here on; ``each`` those of one row.
    sized = cut(counted.withColumnRenamed("size", "each").withColumn("size", F.col("each") * F.col("rows")).withColumn("grade", F.when(F.col("each") > 0, grade(F.col("each")))))
    # A few hundred sums a source come to the driver, as a configuration of the mix has.
    words: dict[str | None, dict[int, int]] = {}
    for r in sized.groupBy("source", "grade").agg(F.sum("size").alias("n")).collect():
        words.setdefault(r["source"], {})[r["grade"]] = int(r["n"])
    sums = [(s, sum(n for n in g.values())) for s, g in words.items()]
    goal = targets(sums, weights, most)
    schema = T.StructType([T.StructField("source_", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType()), T.StructField("factor", T.DoubleType())])
    rows = [(s, n, goal[s], factor({k: v for k, v in words[s].items() if k is not None}, goal[s], most, lean) if n else 0.0) for s, n in sums]
    named = sized.join(F.broadcast(spark.createDataFrame(rows, schema)), F.col("source").eqNullSafe(F.col("source_"))).drop("source_")
    worth = F.coalesce(F.least(F.lit(float(most)), F.col("factor") * F.pow(F.lit(2.0), F.lit(lean / GRADES) * F.col("grade"))), F.lit(0.0))
    named = named.withColumn("worth", F.round(worth, 12)).withColumn("whole", F.floor("worth")).withColumn("part", F.col("worth") - F.col("whole"))
    named = named.withColumn("turn", F.col("text_.h")).withColumn("octave", F.coalesce(F.floor(F.col("grade") / GRADES), F.lit(-1)).cast("int"))
    split = (F.col("part") > 0) & (F.col("size") > 0)
    drawn = named.where(split)
    rest = named.where(~split).withColumn("picked", F.lit(False))
    strata = drawn.groupBy("source", "octave").agg(F.sum(F.col("size") * F.col("part")).alias("goal"))
    strata = strata.select(F.col("source").alias("s_"), F.col("octave").alias("o_"), "goal")
    keyed = drawn.join(strata, F.col("source").eqNullSafe(F.col("s_")) & (F.col("octave") == F.col("o_"))).drop("s_", "o_").withColumn("key", pareto_key(F.col("part"), seed))
    first = cut(take_first(keyed, ["source", "octave"], "goal").drop("goal"))
    # What a source is short of (or has above) its fractions' words is settled among its smaller documents.
    gap = first.groupBy("source").agg((F.sum(F.col("size") * F.col("part")) - F.sum(F.when(F.col("picked"), F.col("size")).otherwise(0))).alias("gap")).select(F.col("source").alias("s_"), "gap")
    told = first.join(F.broadcast(gap), F.col("source").eqNullSafe(F.col("s_"))).drop("s_")
    movable = (F.col("size") <= F.abs("gap")) & (F.col("picked") == (F.col("gap") < 0))
    moved = take_first(told.where(movable).withColumn("goal", F.abs("gap")).withColumn("was", F.col("picked")).drop("picked").withColumn("key", F.when(F.col("was"), 1 - F.col("key") - 1e-16).otherwise(F.col("key"))), ["source"], "goal")
    moved = moved.withColumn("picked", F.col("was") != F.col("picked"))
    cols = ["doc_id", "source", "text_", F.col("each").alias("size"), "rows", "source_size", "target", (F.col("whole") + F.col("picked").cast("long")).alias("copies")]
    return told.where(~movable).select(cols).unionByName(moved.select(cols)).unionByName(rest.select(cols))


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = MOST, seed: int = SEED, lean: float = LEAN) -> DataFrame:
    """Every row with its size, its source's words and target, and the words the mix takes of it."""
    rows = _units(docs, weights, most, seed, lean).withColumn("taken", F.col("size") * F.col("copies"))
    return rows.withColumn("row_", F.explode(F.sequence(F.lit(1), F.col("rows")))).select("doc_id", "size", "source", "source_size", "target", "taken")


def _counted(docs: DataFrame, weights: tuple[float, ...], most: float, seed: int, lean: float) -> DataFrame:
    """(row, copies) for the rows that the mix takes; columns stay inside ``row``, so that no name clashes."""
    taken = _units(docs, weights, most, seed, lean).where("copies > 0 AND size > 0").select(F.struct("doc_id", "source", "text_").alias("id"), "copies")
    text = F.struct(F.xxhash64("text").alias("h"), F.col("text").isNull().alias("none")).alias("text_")
    rows = docs.select(F.struct("*").alias("row"), F.struct("doc_id", "source", text).alias("id"))
    return rows.join(taken.select(F.col("id").alias("of"), "copies"), F.col("id").eqNullSafe(F.col("of"))).select("row", "copies")


def pick(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = MOST, seed: int = SEED, lean: float = LEAN, column: str = "copies") -> DataFrame:
    """The documents of the mix, once each, all columns kept; ``column`` has the number of times to read them."""
    keep = [F.col("row").getField(c).alias(c) for c in docs.columns if c != column]
    return _counted(docs, weights, most, seed, lean).select(*keep, F.col("copies").alias(column))


def repeated(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = MOST, seed: int = SEED, lean: float = LEAN) -> DataFrame:
    """The documents of the mix, as often as it takes each, with the columns they have."""
    counted = _counted(docs, weights, most, seed, lean)
    return counted.select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("time")).select(*(F.col("row").getField(c).alias(c) for c in docs.columns))
