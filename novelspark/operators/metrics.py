"""Accuracy and cost. Scored rows are (doc_id, distance, match_id, truth_id): novel is the positive class, ``truth_id`` null means novel."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

C_MISS, C_FA, P_TARGET = 1.0, 0.1, 0.02


def confusion(decided: DataFrame) -> DataFrame:
    """One row: tp, fn, fp, tn from (is_novel, truth_id)."""
    novel = F.col("truth_id").isNull()
    return decided.agg(
        F.count_if(novel & F.col("is_novel")).alias("tp"), F.count_if(novel & ~F.col("is_novel")).alias("fn"),
        F.count_if(~novel & F.col("is_novel")).alias("fp"), F.count_if(~novel & ~F.col("is_novel")).alias("tn"),
    )


def cost(p_miss: Column, p_fa: Column, c_miss: float = C_MISS, c_fa: float = C_FA, p_target: float = P_TARGET) -> Column:
    """Normalised detection cost; the cheaper of the two constant systems costs 1."""
    least = min(c_miss * p_target, c_fa * (1 - p_target))
    return (F.lit(c_miss * p_target) * p_miss + F.lit(c_fa * (1 - p_target)) * p_fa) / F.lit(least)


def rates(counts: DataFrame) -> DataFrame:
    """Miss rate and both readings of the false-alarm rate, with the cost."""
    miss, old = F.try_divide("fn", F.col("tp") + F.col("fn")), F.try_divide("fp", F.col("fp") + F.col("tn"))
    out = counts.select("*", miss.alias("p_miss"), old.alias("p_fa"), F.try_divide("fp", F.col("tp") + F.col("fp")).alias("p_fa_flagged"))
    return out.withColumn("cost", cost(F.coalesce("p_miss", F.lit(0.0)), F.coalesce("p_fa", F.lit(0.0))))


def det_curve(scored: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(threshold, p_miss, p_fa, cost): a point for every distinct distance, novel meaning distance >= threshold.

    Rows are counted by distance first (distances have six decimals), so the running sum sees at most a million rows.
    """
    novel = F.col("truth_id").isNull()
    at = scored.groupBy(*keys, F.col("distance").alias("threshold")).agg(F.count_if(novel).alias("n_new"), F.count_if(~novel).alias("n_old"))
    before = W.partitionBy(*keys).orderBy("threshold").rowsBetween(W.unboundedPreceding, -1)
    whole = W.partitionBy(*keys)
    out = at.select(
        *keys, "threshold", F.coalesce(F.sum("n_new").over(before), F.lit(0)).alias("missed"), F.coalesce(F.sum("n_old").over(before), F.lit(0)).alias("caught"),
        F.sum("n_new").over(whole).alias("new"), F.sum("n_old").over(whole).alias("old"),
    )
    # the point above all distances: everything is called old
    ends = out.groupBy(*keys).agg(F.lit(2.0).alias("threshold"), F.max("new").alias("missed"), F.max("old").alias("caught"), F.max("new").alias("new"), F.max("old").alias("old"))
    points = out.unionByName(ends).select(*keys, "threshold", F.coalesce(F.try_divide("missed", "new"), F.lit(0.0)).alias("p_miss"), F.coalesce(1 - F.try_divide("caught", "old"), F.lit(0.0)).alias("p_fa"))
    return points.withColumn("cost", cost(F.col("p_miss"), F.col("p_fa")))


def det_grid(scored: DataFrame, steps: int = 20) -> DataFrame:
    """The curve at thresholds 0, 1/steps ... 1: each row is counted in its cell, cells are summed up."""
    novel = F.col("truth_id").isNull()
    cell = F.least(F.ceil(F.col("distance") * steps), F.lit(steps)).cast("int")
    cells = scored.groupBy(F.when(F.col("distance") * steps == cell, cell + 1).otherwise(cell).alias("cell")).agg(F.count_if(novel).alias("a"), F.count_if(~novel).alias("b"))
    grid = scored.sparkSession.range(steps + 1).select(F.col("id").cast("int").alias("step"))
    joined = grid.join(F.broadcast(cells), F.col("cell") <= F.col("step"), "left").groupBy("step").agg(F.coalesce(F.sum("a"), F.lit(0)).alias("missed"), F.coalesce(F.sum("b"), F.lit(0)).alias("caught"))
    total = scored.agg(F.count_if(novel).alias("new"), F.count_if(~novel).alias("old"))
    return joined.join(F.broadcast(total)).select(
        (F.col("step") / steps).alias("threshold"), F.coalesce(F.try_divide("missed", "new"), F.lit(0.0)).alias("p_miss"), F.coalesce(1 - F.try_divide("caught", "old"), F.lit(0.0)).alias("p_fa")
    )


def best_point(curve: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """The lowest-cost point of each curve, ties to the smaller threshold."""
    return curve.groupBy(*keys).agg(F.min(F.struct(F.round("cost", 9).alias("cost"), "threshold", "p_miss", "p_fa")).alias("b")).select(*keys, "b.*")


def area(curve: DataFrame) -> DataFrame:
    """Area under the curve by trapezoids, and the point where both rates are nearest to each other."""
    by = W.orderBy("p_miss", F.desc("p_fa"))
    steps = curve.select("p_miss", "p_fa", (F.col("p_miss") - F.lag("p_miss").over(by)).alias("dx"), (F.col("p_fa") + F.lag("p_fa").over(by)).alias("h"))
    return steps.agg(F.sum(F.col("dx") * F.col("h") / 2).alias("auc"), F.min(F.struct(F.round(F.abs(F.col("p_miss") - F.col("p_fa")), 9).alias("gap"), ((F.col("p_miss") + F.col("p_fa")) / 2).alias("rate"))).alias("e")).select("auc", F.col("e.rate").alias("equal_error"))


def probit(p: Column) -> Column:
    """Normal quantile, for axes on a Gaussian scale: the rational approximation of Abramowitz and Stegun 26.2.23."""
    tail = F.sqrt(-2 * F.ln(F.greatest(F.lit(1e-12), F.least(p, 1 - p))))
    # fixed values: the approximation's coefficients
    above = 2.515517 + tail * (0.802853 + tail * 0.010328)
    below = 1 + tail * (1.432788 + tail * (0.189269 + tail * 0.001308))
    return (tail - above / below) * F.when(p < 0.5, -1.0).otherwise(1.0)


def match_accuracy(decided: DataFrame) -> DataFrame:
    """Among truly old rows: called old, and with the right identity."""
    old = F.col("truth_id").isNotNull()
    return decided.agg(F.count_if(old).alias("n_old"), F.count_if(old & ~F.col("is_novel")).alias("called_old"), F.count_if(old & (F.col("match_id") == F.col("truth_id"))).alias("right_id"))


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """Gain of b over a at their best points, absolute and relative."""
    left, right = (x.select(F.col("p_miss").alias(f"miss_{n}"), F.col("p_fa").alias(f"fa_{n}"), F.col("cost").alias(f"cost_{n}")) for x, n in ((a, "a"), (b, "b")))
    gain = lambda m: [(F.col(f"{m}_a") - F.col(f"{m}_b")).alias(f"{m}_gain"), F.try_divide(F.col(f"{m}_a") - F.col(f"{m}_b"), F.col(f"{m}_a")).alias(f"{m}_rel_gain")]
    return left.join(right).select("*", *gain("miss"), *gain("fa"), *gain("cost"))


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of queries whose exact nearest distance the hashed search reaches. Both are (q, distance, h)."""
    joined = exact.select("q", F.col("distance").alias("d")).join(found.select("q", F.col("distance").alias("f")), "q", "left")
    return joined.agg(F.count("*").alias("n"), F.count_if(F.coalesce(F.col("f") <= F.col("d"), F.lit(False))).alias("hit")).withColumn("recall", F.try_divide("hit", "n"))


def bootstrap(decided: DataFrame, rounds: int = 50, seed: int = 1) -> DataFrame:
    """Rates over ``rounds`` resamples: each row's number of copies in a round is a Poisson value from a hash of row, round and seed."""
    each = decided.select("doc_id", "is_novel", "truth_id", F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    u = (F.conv(F.substring(F.md5(F.concat_ws("|", "doc_id", "round", F.lit(seed))), 1, 8), 16, 10).cast("double") + 0.5) / float(1 << 32)
    # cumulated Poisson(1) chances: exp(-1) times 1, 2, 2.5, 2.666...
    copies = sum((F.when(u > c, 1).otherwise(0) for c in (0.367879, 0.735759, 0.919699, 0.981012, 0.996340)), F.lit(0))
    novel = F.col("truth_id").isNull()
    weighted = each.withColumn("c", copies)
    sums = weighted.groupBy("round").agg(*[F.sum(F.when(cond, F.col("c")).otherwise(0)).alias(name) for name, cond in (("tp", novel & F.col("is_novel")), ("fn", novel & ~F.col("is_novel")), ("fp", ~novel & F.col("is_novel")), ("tn", ~novel & ~F.col("is_novel")))])
    return rates(sums)


def timed(action: Callable[[], object]) -> float:
    start = time.perf_counter()
    action()
    return time.perf_counter() - start
