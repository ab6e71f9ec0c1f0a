"""Merge rates, costs and times."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagewise.plans.trials import nodes


def _rate(total: F.Column, unique: F.Column) -> F.Column:
    return F.round(total / unique, 6)


def merge_rate(segments: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Total and unique steps of all trials, each at its maximum: (by.., trials, total_steps, unique_steps, nodes, rate).

    A node's unique steps are its furthest reach less its start, so no step is ever expanded.
    Both aggregations are algebraic; a root shared by all trials is merged map-side.
    """
    per_node = segments.groupBy(*by, "path").agg(
        F.sum(F.col("end") - F.col("start")).alias("t"), (F.max("end") - F.min("start")).alias("u"),
        F.count(F.when(F.col("k") == 0, 1)).alias("roots"),
    )
    return per_node.groupBy(*by).agg(
        F.sum("roots").alias("trials"), F.sum("t").alias("total_steps"), F.sum("u").alias("unique_steps"), F.count("*").alias("nodes")
    ).withColumn("rate", _rate(F.col("total_steps"), F.col("unique_steps")))


def merge_bruteforce(segments: DataFrame) -> DataFrame:
    """The same by counting distinct (history, step) pairs; only for checks on small inputs."""
    steps = segments.select("path", F.explode(F.sequence("start", F.col("end") - 1)).alias("step"))
    return steps.groupBy("path", "step").agg(F.count("*").alias("c")).agg(F.sum("c").alias("total_steps"), F.count("*").alias("unique_steps"))


def kwise_rate(segments: DataFrame, studies: list[list[str]]) -> DataFrame:
    """For each set of studies: (k, total, unique, within_unique, rate), pooled and within studies; segments are read once.

    A node and study make one row, which is then copied to the sets that hold the study.
    """
    fine = segments.groupBy("study", "path").agg(F.sum(F.col("end") - F.col("start")).alias("t"), F.min("start").alias("s"), F.max("end").alias("e"))
    sets = F.array(*[F.when(F.col("study").isin(own), F.lit(n)) for n, own in enumerate(studies)])
    wide = fine.withColumn("at", F.explode(F.filter(sets, lambda x: x.isNotNull())))
    node = wide.groupBy("at", "path").agg(F.sum("t").alias("t"), (F.max("e") - F.min("s")).alias("u"), F.sum(F.col("e") - F.col("s")).alias("w"))
    out = node.groupBy("at").agg(F.sum("t").alias("total"), F.sum("u").alias("unique"), F.sum("w").alias("within_unique"))
    k = F.element_at(F.array(*[F.lit(len(own)) for own in studies]), F.col("at") + 1).cast("long").alias("k")
    return out.select(k, "total", "unique", "within_unique", _rate(F.col("total"), F.col("unique")).alias("rate"))


def pairwise_rates(segments: DataFrame) -> DataFrame:
    """(study_a, study_b, rate) of each two studies: steps saved come from nodes both have."""
    per = segments.groupBy("study", "path").agg(F.sum(F.col("end") - F.col("start")).alias("t"), (F.max("end") - F.min("start")).alias("u"))
    alone = per.groupBy("study").agg(F.sum("t").alias("t"), F.sum("u").alias("u"))
    a, b = per.select(F.col("study").alias("study_a"), "path", F.col("u").alias("ua")), per.select(F.col("study").alias("study_b"), "path", F.col("u").alias("ub"))
    shared = a.join(b, "path").where("study_a < study_b").groupBy("study_a", "study_b").agg(F.sum(F.least("ua", "ub")).alias("saved"))
    # one row per study on either side
    x, y = alone.select(F.col("study").alias("study_a"), F.col("t").alias("ta"), F.col("u").alias("ua")), alone.select(F.col("study").alias("study_b"), F.col("t").alias("tb"), F.col("u").alias("ub"))
    pairs = x.join(y, F.col("study_a") < F.col("study_b")).join(shared, ["study_a", "study_b"], "left")
    return pairs.select("study_a", "study_b", _rate(F.col("ta") + F.col("tb"), F.col("ua") + F.col("ub") - F.coalesce("saved", F.lit(0))).alias("rate"))


def cost_rate(segments: DataFrame, seconds: DataFrame) -> DataFrame:
    """Merge rate weighted by seconds(cfg, sec) per step; an unknown configuration costs the mean of the known ones."""
    mean = F.broadcast(seconds.agg(F.avg("sec").alias("mean")))  # one row
    per = nodes(segments).select("path", "cfg", (F.col("reach") - F.col("start")).alias("u")).join(
        segments.groupBy("path").agg(F.sum(F.col("end") - F.col("start")).alias("t")), "path"
    )
    told = per.groupBy("cfg").agg(F.sum("t").alias("t"), F.sum("u").alias("u")).join(seconds, "cfg", "left").crossJoin(mean)
    sec = F.coalesce("sec", "mean")
    out = told.agg(F.round(F.sum(F.col("t") * sec), 6).alias("cost"), F.round(F.sum(F.col("u") * sec), 6).alias("unique_cost"))
    return out.withColumn("rate", _rate(F.col("cost"), F.col("unique_cost")))


def explored_rate(segments: DataFrame, reached: DataFrame) -> DataFrame:
    """The merge rate of what a tuner really asked for: segments cut at the step that each trial of reached(study, trial, step) got to."""
    known = segments.join(reached.select("study", "trial", F.col("step").alias("upto")), ["study", "trial"]).where("start < upto")
    return merge_rate(known.withColumn("end", F.least("end", "upto")).drop("upto"))


def merge_rollup(segments: DataFrame, levels: list[str], cube: bool = False) -> DataFrame:
    """Rates of every level; nodes are merged per level, from one partial row per node and finest key.

    segments has the level columns.  The expansion acts on those partial rows, not on segments.
    """
    fine = segments.groupBy(*levels, "path").agg(F.sum(F.col("end") - F.col("start")).alias("t"), F.min("start").alias("s"), F.max("end").alias("e"))
    from itertools import combinations

    sets = [tuple(levels[:n]) for n in range(len(levels), -1, -1)] if not cube else [c for n in range(len(levels), -1, -1) for c in combinations(levels, n)]
    kept = F.array(*[F.struct(*[(F.col(c) if c in own else F.lit(None).cast("string")).alias(c) for c in levels], F.lit(sum(1 << (len(levels) - 1 - i) for i, c in enumerate(levels) if c not in own)).cast("long").alias("grouping_id")) for own in sets])
    wide = fine.select(F.explode(kept).alias("g"), "path", "t", "s", "e").select("g.*", "path", "t", "s", "e")
    node = wide.groupBy(*levels, "grouping_id", "path").agg(F.sum("t").alias("t"), (F.max("e") - F.min("s")).alias("u"))
    return node.groupBy(*levels, "grouping_id").agg(F.sum("t").alias("total"), F.sum("u").alias("unique")).withColumn("rate", _rate(F.col("total"), F.col("unique")))


def makespan(placements: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """placements(by.., worker, stage_id, t0, t1) -> end-to-end time and the time workers were held."""
    return placements.groupBy(*by).agg((F.max("t1") - F.min("t0")).alias("makespan"), F.sum(F.col("t1") - F.col("t0")).alias("worker_time"))


def transitions(placements: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Stages that do not continue the one before them on their worker, and so load a checkpoint."""
    last = F.lag("stage_id").over(Window.partitionBy(*by, "worker").orderBy("t0", "t1"))
    moved = F.col("parent").isNotNull() & ~F.col("parent").eqNullSafe(F.col("last"))
    return placements.withColumn("last", last).groupBy(*by).agg(F.count_if(moved).alias("transitions"))


def best(metrics: DataFrame, name: str = "value") -> DataFrame:
    """metrics(trial, step, value) -> the trial and step of the largest value; the smallest trial wins a tie."""
    return metrics.agg(F.max_by(F.struct("trial", "step", name), F.struct(F.col(name), -F.col("trial"), -F.col("step"))).alias("b")).select("b.*")


def auc_udaf():
    """(score, label 0/1) -> the share of pairs of a 1 and a 0 that the score orders rightly, ties half: an aggregate function for metrics that need a whole group.

    A group is one trial's evaluation, which one task holds.
    """

    @F.pandas_udf("double")
    def auc(score: pd.Series, label: pd.Series) -> float:
        rank, ones = score.rank(), label == 1
        n, m = int(ones.sum()), int((~ones).sum())
        return float((rank[ones].sum() - n * (n + 1) / 2) / (n * m)) if n and m else None

    return auc


def speedup(base: DataFrame, ours: DataFrame, on: list[str], columns: list[str]) -> DataFrame:
    right = ours.select(*on, *[F.col(c).alias(f"our_{c}") for c in columns])
    return base.join(right, on).select(*on, *[F.round(F.col(c) / F.col(f"our_{c}"), 6).alias(f"{c}_speedup") for c in columns])


def counts(segments: DataFrame) -> DataFrame:
    n = nodes(segments)
    return segments.agg(F.count(F.when(F.col("k") == 0, 1)).alias("trials"), F.count("*").alias("segments")).crossJoin(n.agg(F.count("*").alias("nodes"), F.max("depth").alias("max_depth")))
