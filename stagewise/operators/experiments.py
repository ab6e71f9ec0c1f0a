"""Whole experiments: what each way of running a study costs on a cluster, and what it finds.

Three ways are compared: ``external``, a tuner of independent trials that hands trials to workers one by one; ``trial``, the
chains of this engine without any sharing; and ``stage``, with it.  Metrics come from real training, times from the
virtual clock of :mod:`stagewise.operators.simulate`.
"""

from __future__ import annotations

import heapq
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagewise.operators import measures, simulate, training, tuners
from stagewise.plans import forest, schedule
from stagewise.plans import trials as T
from stagewise.store import Scratch

WAYS = ("external", "trial", "stage")


def curves(segments: DataFrame, source: tuple[DataFrame, DataFrame], classes: int, steps: list[int], model: type = training.Softmax, measure: str = "value", iteration: int = 1, shared: bool = True) -> DataFrame:
    """(study, trial, step, value) of all trials at some steps, by shared training that resumes at each of them; a step is ``iteration`` mini-batches."""
    learn, held = source
    scratch = Scratch(segments.sparkSession, "curves")
    data, own, out, lo = training.fit_sample(learn), segments.withColumn("ckpt", F.lit(None).cast("binary")), None, 0
    for hi in steps:
        done = scratch.save(training.train(own, data, classes, shared, lo, hi, model=model, iteration=iteration), f"state-{hi}")
        told = scratch.save(training.scores(done, held, model).select("study", "trial", F.lit(hi).cast("long").alias("step"), F.round(measure, 6).alias("value")), f"values-{hi}")
        out = told if out is None else out.unionByName(told)
        own, lo = own.drop("ckpt").join(done.select("study", "trial", "ckpt"), ["study", "trial"]), hi
    return out


def clipped(segments: DataFrame, lo: int, hi: int) -> DataFrame:
    """The part of trials from one step to another; what begins at ``lo`` begins at a checkpoint."""
    own = segments.where((F.col("start") < hi) & (F.col("end") > lo))
    return own.withColumns({
        "parent": F.when(F.col("start") > lo, F.col("parent")), "start": F.greatest("start", F.lit(lo).cast("long")), "end": F.least("end", F.lit(hi).cast("long")),
    })


def chains_of(segments: DataFrame, way: str) -> DataFrame:
    """(stage, parent, leaf, cost) of some trials run in one of the WAYS; a step costs 1."""
    if way == "external":
        name = F.concat(F.col("study"), F.lit("/"), F.format_string("%012d", F.col("trial")))
        whole = segments.groupBy(name.alias("stage")).agg(F.sum(F.col("end") - F.col("start")).cast("double").alias("cost"))
        return whole.select("stage", F.lit(None).cast("string").alias("parent"), F.col("stage").alias("leaf"), "cost")
    g = T.salted(segments, "none" if way == "trial" else "plan")
    stages = schedule.costs(forest.merge_trials(g))
    up = stages.select(schedule.stage_id(F.col("path"), F.col("hi")).alias("stage"), schedule.stage_id(F.col("parent_path"), F.col("parent_hi")).alias("parent"))
    return schedule.elected_leaves(stages, T.lines(g)).join(up, "stage").select("stage", "parent", "leaf", "cost")


def timed(parts: list[tuple[str, DataFrame]], workers: int, extra: float = 0.0) -> DataFrame:
    """parts: (way, segments), one after the other where a way comes again -> (way, worker_time, makespan, transitions); ``extra`` steps of the winner come last."""
    rows = [chains_of(g, way).withColumn("study", F.lit(f"{way}/{k}")) for k, (way, g) in enumerate(parts)]
    told = simulate.run(reduce(DataFrame.unionByName, rows), [("chains", workers), ("breadth", workers)])
    told = told.withColumn("way", F.substring_index("study", "/", 1)).where((F.col("way") == "external") == (F.col("policy") == "breadth"))
    return told.groupBy("way").agg((F.sum("busy") + extra).alias("worker_time"), (F.sum("makespan") + extra).alias("makespan"), F.sum("transitions").alias("transitions"))


def grid_study(segments: DataFrame, workers: int, extra: float) -> DataFrame:
    return timed([(way, segments) for way in WAYS], workers, extra)


def grid_studies(segments: DataFrame, workers: int, extra: float) -> DataFrame:
    """:func:`grid_study` of each study, with a plan and a cluster of its own: (study, way, worker_time, makespan, transitions); studies' names hold neither ~ nor /."""
    own = T.salted(segments, "study")
    name = {"external": F.substring_index("stage", "/", 1), "trial": F.expr("substring(substring_index(stage, '~', 1), 2)")}
    name["stage"] = name["trial"]
    rows = [chains_of(own, way).withColumn("study", F.concat(F.lit(f"{way}/"), name[way])) for way in WAYS]
    told = simulate.run(reduce(DataFrame.unionByName, rows), [("chains", workers), ("breadth", workers)])
    told = told.withColumn("way", F.substring_index("study", "/", 1)).where((F.col("way") == "external") == (F.col("policy") == "breadth"))
    return told.select(F.substring_index("study", "/", -1).alias("study"), "way", (F.col("busy") + extra).alias("worker_time"), (F.col("makespan") + extra).alias("makespan"), "transitions")


def halving_study(segments: DataFrame, metrics: DataFrame, eta: int, least: int, most: int, workers: int, extra: float) -> tuple[DataFrame, DataFrame]:
    """(times, decisions) of synchronous halving: a barrier after each rung."""
    decisions = Scratch(segments.sparkSession, "halving").save(tuners.halving(metrics, eta, least, most), "decisions")
    steps, parts = tuners.rungs(eta, least, most), []
    for lo, hi in zip([0, *steps], steps):
        alive = segments.join(decisions.where(F.col("rung") == hi).select("study", "trial"), ["study", "trial"], "left_semi")
        parts += [(way, clipped(alive, lo, hi)) for way in WAYS]
    return timed(parts, workers, extra), decisions


def simulate_async(ways: dict[int, list[tuple[str, int, int]]], values: dict[tuple[int, int], float], eta: int, steps: list[int], workers: int) -> tuple[float, float, list[tuple[int, int]], int]:
    """Asynchronous halving on a virtual clock: ways: trial -> its (node, start, end) in order -> (makespan, busy, (trial, step reached) of all, loads).

    A free worker takes a promotion if there is one, else the next trial.  It trains what nobody has trained or is training of
    the trial's way to its next rung, and is held for those steps; the result is there when all of them are.
    """
    tuner = tuners.AsyncHalving(eta, steps)
    up = dict(zip(steps, steps[1:]))
    queue, fresh = [], sorted(ways)
    at = {t: 0 for t in ways}
    covered: dict[str, tuple[int, float]] = {}
    running: list[tuple[float, int, int, bool]] = []  # (time, trial, step, whether it holds a worker)
    idle, now, busy, loads, end = workers, 0.0, 0.0, 0, 0.0
    fresh.reverse()
    while True:
        while idle and (queue or fresh):
            trial, step = queue.pop(0) if queue else (fresh.pop(), steps[0])
            ready, own = now, 0.0
            for node, a, b in ways[trial]:
                a, b = max(a, at[trial]), min(b, step)
                if a >= b:
                    continue
                done, when = covered.get(node, (a, now))
                if done >= b:
                    ready = max(ready, when - (done - b))
                else:
                    ready = max(ready, when) if done > a else ready
                    own += b - max(a, done)
                    ready += b - max(a, done)
                    covered[node] = (b, ready)
            busy, loads = busy + own, loads + (own > 0)
            at[trial] = step
            idle -= own > 0
            heapq.heappush(running, (ready, trial, step, own > 0))
        if not running:
            break
        now, trial, step, held = heapq.heappop(running)
        idle, end = idle + held, max(end, now)
        queue += [(t, up[s]) for t, s in tuner.report(trial, step, values[trial, step])]
    return end, busy, sorted(at.items()), loads


def async_study(segments: DataFrame, metrics: DataFrame, eta: int, least: int, most: int, workers: int, extra: float) -> tuple[DataFrame, DataFrame]:
    """(times, reached(way, study, trial, step)) of asynchronous halving; the trials of one client are one task."""
    steps = tuners.rungs(eta, least, most)
    sides = [T.salted(segments, "none" if way != "stage" else "plan").withColumn("way", F.lit(way)) for way in WAYS]
    left = reduce(DataFrame.unionByName, sides).select("way", "study", "trial", "path", "start", "end")
    right = metrics.crossJoin(F.broadcast(segments.sparkSession.createDataFrame([(w,) for w in WAYS], "way string")))

    def one(own: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        number = {k: i for i, k in enumerate(sorted(set(zip(own["study"], own["trial"].tolist()))))}
        ways: dict[int, list] = {}
        for r in own.sort_values("start").itertuples():
            ways.setdefault(number[r.study, r.trial], []).append((r.path, r.start, r.end))
        values = {(number[r.study, r.trial], r.step): r.value for r in told.itertuples()}
        makespan, busy, reached, loads = simulate_async(ways, values, eta, steps, workers)
        name = {i: k for k, i in number.items()}
        rows = [(own["way"].iloc[0], *name[t], step, makespan + extra, busy + extra, loads) for t, step in reached if step]
        return pd.DataFrame(rows, columns=["way", "study", "trial", "step", "makespan", "worker_time", "transitions"])

    out = left.groupBy("way").cogroup(right.groupBy("way")).applyInPandas(one, "way string, study string, trial long, step long, makespan double, worker_time double, transitions long")
    out = Scratch(segments.sparkSession, "async").save(out, "runs")
    return out.groupBy("way").agg(F.first("worker_time").alias("worker_time"), F.first("makespan").alias("makespan"), F.first("transitions").alias("transitions")), out.select("way", "study", "trial", "step")


def compared(times: DataFrame, workload: str, on: tuple[str, ...] = ()) -> DataFrame:
    """Times with their ratio to those of the external tuner."""
    rows = times.withColumn("workload", F.lit(workload))
    keys = ["workload", *on]
    base = rows.where("way = 'external'").select(*keys, "worker_time", "makespan")
    return rows.join(measures.speedup(base.join(rows.select(*keys, "way"), keys), rows, [*keys, "way"], ["worker_time", "makespan"]), [*keys, "way"])


def explored(segments: DataFrame, reached: DataFrame) -> float:
    return measures.explored_rate(segments, reached).first()["rate"]


def last_steps(decisions: DataFrame) -> DataFrame:
    """(study, trial, step) that halving took each trial to."""
    w = Window.partitionBy("study", "trial").orderBy(F.desc("rung"))
    return decisions.withColumn("r", F.row_number().over(w)).where("r = 1").select("study", "trial", F.col("rung").alias("step"))
