"""Statistics over a frame of runs: algo, graph, k, seed, p, secs, cut, max_block_w, strict_cap, status, phase."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

INSTANCE = ["graph", "k"]


def geo_mean(c: Column | str) -> Column:
    """Geometric mean; zeros count as one."""
    return F.exp(F.avg(F.log(F.greatest(F.col(c) if isinstance(c, str) else c, F.lit(1e-9)))))


def harm_mean(c: Column | str) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    return F.count(c) / F.sum(1 / c)


def with_time_limit(runs: DataFrame, limit: float) -> DataFrame:
    """Timed-out runs take the limit as their time."""
    return runs.withColumn("secs", F.when(F.col("status") == "timeout", F.lit(limit)).otherwise(F.least("secs", F.lit(limit))))


def agg_seeds(runs: DataFrame) -> DataFrame:
    """Arithmetic means over seeds, a row for each algorithm and instance."""
    return runs.groupBy("algo", *INSTANCE).agg(F.avg("secs").alias("secs"), F.avg("cut").alias("cut"), F.count(F.lit(1)).alias("seeds"))


def imbalanced() -> Column:
    return (F.col("status") == "ok") & (F.col("max_block_w") > F.col("strict_cap"))


def outcome_counts(runs: DataFrame) -> DataFrame:
    ok = F.col("status") == "ok"
    return runs.groupBy("algo").agg(F.count_if(F.col("status") == "timeout").alias("timeouts"), F.count_if(F.col("status") == "crash").alias("crashes"), F.count_if(imbalanced()).alias("imbalanced"), F.count_if(ok & ~imbalanced()).alias("feasible"))


def mark_infeasible(runs: DataFrame) -> DataFrame:
    """(algo, graph, k, infeasible): all runs of the instance failed or are imbalanced."""
    return runs.groupBy("algo", *INSTANCE).agg(F.bool_and((F.col("status") != "ok") | imbalanced()).alias("infeasible"))


def performance_profile(per_instance: DataFrame, taus: list[float], value: str = "cut") -> DataFrame:
    """(algo, tau, share): on what share of the instances an algorithm is within tau of the best; null values never are."""
    best = per_instance.withColumn("best", F.min(value).over(W.partitionBy(*INSTANCE)))
    grid = F.broadcast(per_instance.sparkSession.createDataFrame([(float(t),) for t in taus], "tau double"))
    hit = F.coalesce(F.col(value) <= F.col("tau") * F.col("best"), F.lit(False))
    return best.crossJoin(grid).groupBy("algo", "tau").agg(F.avg(hit.cast("double")).alias("share"))


def share_best(per_instance: DataFrame, value: str = "cut") -> DataFrame:
    return performance_profile(per_instance, [1.0], value).select("algo", "share")


def at_least_twice(per_instance: DataFrame, value: str = "cut") -> DataFrame:
    """(algo, share): instances on which the value is more than twice the best."""
    return performance_profile(per_instance, [2.0], value).select("algo", (1 - F.col("share")).alias("share"))


def rolling_geo_mean(rows: DataFrame, size: str, value: str, span: int = 50) -> DataFrame:
    """(algo, size, rolling): geometric mean over the last ``span`` instances in order of size."""
    w = W.partitionBy("algo").orderBy(size, *INSTANCE).rowsBetween(-(span - 1), 0)
    return rows.withColumn("rolling", F.exp(F.avg(F.log(F.greatest(F.col(value), F.lit(1e-9)))).over(w)))


def relative_to(per_instance: DataFrame, ours: str, value: str) -> DataFrame:
    """(algo, relative): geometric mean of an algorithm's value over ours, on instances that both have."""
    mine = per_instance.where((F.col("algo") == ours) & F.col(value).isNotNull()).select(*INSTANCE, F.col(value).alias("ours"))
    both = per_instance.where(F.col(value).isNotNull()).join(mine, INSTANCE)
    return both.groupBy("algo").agg(F.exp(F.avg(F.log(F.greatest(F.col(value), F.lit(1)) / F.greatest("ours", F.lit(1))))).alias("relative"))


def relative_time(runs: DataFrame, ours: str) -> DataFrame:
    """On instances without crashes."""
    return relative_to(agg_seeds(runs.where("status <> 'crash'")).withColumn("secs", F.col("secs") * 1e6), ours, "secs")


def relative_cut(runs: DataFrame, ours: str) -> DataFrame:
    """On instances without crashes and timeouts."""
    return relative_to(agg_seeds(runs.where("status = 'ok'")), ours, "cut")


def speedup(runs: DataFrame, seconds: str = "secs") -> DataFrame:
    """(graph, k, p, t1, speedup): self-relative, per instance."""
    mean = runs.groupBy(*INSTANCE, "p").agg(F.avg(seconds).alias("t"))
    one = mean.where("p = 1").select(*INSTANCE, F.col("t").alias("t1"))
    return mean.join(one, INSTANCE).select(*INSTANCE, "p", "t1", (F.col("t1") / F.col("t")).alias("speedup"))


def speedup_by_phase(runs: DataFrame) -> DataFrame:
    """(phase, p, speedup): harmonic means over instances, for each phase of the map column."""
    rows = runs.select(*INSTANCE, "p", F.explode("phase").alias("name", "t")).groupBy(*INSTANCE, "p", "name").agg(F.avg("t").alias("t"))
    one = rows.where("p = 1").select(*INSTANCE, "name", F.col("t").alias("t1"))
    return rows.join(one, [*INSTANCE, "name"]).groupBy(F.col("name").alias("phase"), "p").agg(harm_mean(F.col("t1") / F.col("t")).alias("speedup"))


def cumulative_speedup(speedups: DataFrame) -> DataFrame:
    """(p, t1, cumulative): harmonic mean over all instances that take t1 or longer on one core."""
    w = W.partitionBy("p").orderBy(F.desc("t1")).rangeBetween(W.unboundedPreceding, W.currentRow)
    return speedups.select("p", "t1", (F.count(F.lit(1)).over(w) / F.sum(1 / F.col("speedup")).over(w)).alias("cumulative"))


def imbalance_percentiles(runs: DataFrame) -> DataFrame:
    """(algo, median, most): how far infeasible finished runs are above the limit."""
    bad = runs.where(imbalanced()).withColumn("ratio", F.col("max_block_w") / F.col("strict_cap"))
    return bad.groupBy("algo").agg(F.percentile("ratio", F.lit(0.5)).alias("median"), F.max("ratio").alias("most"))
