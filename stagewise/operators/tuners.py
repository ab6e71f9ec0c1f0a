"""Tuners as ranks over reported metrics: metrics(study, trial, rung, value)."""

from __future__ import annotations

import bisect
import heapq
import math

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def rungs(eta: int, least: int, most: int) -> list[int]:
    """Steps of the rungs: least * eta**k, the last one clamped to most."""
    out = [least]
    while out[-1] < most:
        out.append(min(most, out[-1] * eta))
    return out


def halving(metrics: DataFrame, eta: int, least: int, most: int) -> DataFrame:
    """Synchronous halving over metrics of all trials at all rung steps: (study, trial, rung, rank, action).

    Of the trials at a rung the best floor(n / eta), one at least, go on; ties by trial.  One task ranks the trials
    of a study at a rung: a client's trials, some millions at most.
    """
    steps = rungs(eta, least, most)
    alive = metrics.select("study", "trial").distinct()
    out = None
    for r, step in enumerate(steps):
        own = metrics.where(F.col("step") == step).join(alive, ["study", "trial"], "left_semi")
        w = Window.partitionBy("study").orderBy(F.desc("value"), "trial")
        ranked = own.withColumn("rank", F.row_number().over(w).cast("long")).withColumn("n", F.count("*").over(Window.partitionBy("study")))
        kept = F.greatest(F.floor(F.col("n") / eta), F.lit(1))
        action = F.lit("finish") if r == len(steps) - 1 else F.when(F.col("rank") <= kept, "promote").otherwise("stop")
        told = ranked.select("study", "trial", F.lit(step).cast("long").alias("rung"), "rank", action.alias("action"))
        out = told if out is None else out.unionByName(told)
        alive = told.where("action = 'promote'").select("study", "trial")
    return out


def milestones(metrics: DataFrame, schedule: list[tuple[int, int]]) -> DataFrame:
    """(iteration, survivors) in turn: (study, trial, rung, rank, action)."""
    alive = metrics.select("study", "trial").distinct()
    out = None
    for step, keep in schedule:
        own = metrics.where(F.col("step") == step).join(alive, ["study", "trial"], "left_semi")
        w = Window.partitionBy("study").orderBy(F.desc("value"), "trial")
        told = own.select("study", "trial", F.lit(step).cast("long").alias("rung"), F.row_number().over(w).cast("long").alias("rank"))
        told = told.withColumn("action", F.when(F.col("rank") <= keep, "promote").otherwise("stop"))
        out = told if out is None else out.unionByName(told)
        alive = told.where("action = 'promote'").select("study", "trial")
    return out


def hyperband(eta: int, least: int, most: int) -> list[dict]:
    """Brackets with their numbers of trials and first steps."""
    top = int(math.floor(math.log(most / least) / math.log(eta) + 1e-9))
    return [{"bracket": s, "trials": math.ceil((top + 1) / (s + 1) * eta**s), "first_step": max(1, round(most * eta ** (-s)))} for s in range(top, -1, -1)]


def median_stop(metrics: DataFrame, grace: int, cohort: int = 3) -> DataFrame:
    """(study, trial, stop_at): the first step where a trial's best so far is below the median of the others' running means.

    The median without one member follows from its own rank and the three middle values of its step, so a row carries no
    other rows.  One task ranks the trials of a study at a step: a client's trials, some millions at most.
    """
    run = Window.partitionBy("study", "trial").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    told = metrics.select("study", "trial", "step", F.avg("value").over(run).alias("mean"), F.max("value").over(run).alias("best"))
    at = Window.partitionBy("study", "step")
    told = told.where(F.col("step") >= grace).withColumns({"r": F.row_number().over(at.orderBy("mean", "trial")), "n": F.count("*").over(at)})
    # the middle places of the n - 1 others; a place at or beyond one's own rank lies one further among all
    low, high = F.floor(F.col("n") / 2).cast("int"), F.floor((F.col("n") + 1) / 2).cast("int")
    told = told.withColumns({"low": low, "high": high})
    told = told.withColumns({f"v{k}": F.max(F.when(F.col("r") == F.col("low") + k, F.col("mean"))).over(at) for k in (0, 1, 2)})

    def value(place: F.Column) -> F.Column:
        k = place + (place >= F.col("r")).cast("int") - F.col("low")
        return F.when(k == 0, F.col("v0")).when(k == 1, F.col("v1")).otherwise(F.col("v2"))

    middle = (value(F.col("low")) + value(F.col("high"))) / 2
    return told.where(F.col("n") > cohort).where(F.col("best") < middle).groupBy("study", "trial").agg(F.min("step").alias("stop_at"))


def population(metrics: DataFrame, step: int, quantile: float = 0.2, seed: int = 1) -> DataFrame:
    """One exploit step: (study, trial, donor): the bottom share copies a donor of the top share, paired by keyed order."""
    own = metrics.where(F.col("step") == step)
    w = Window.partitionBy("study").orderBy(F.desc("value"), "trial")
    ranked = own.select("study", "trial", F.row_number().over(w).alias("r"), F.count("*").over(Window.partitionBy("study")).alias("n"))
    share = F.greatest(F.floor(F.col("n") * quantile), F.lit(1)).cast("int")
    top = ranked.where(F.col("r") <= share).select("study", F.col("trial").alias("donor"), (F.col("r") - 1).alias("slot"))
    pick = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}-{step}-"), F.col("trial").cast("string"))), 1, 8), 16, 10).cast("long")
    low = ranked.where(F.col("r") > F.col("n") - share).select("study", "trial", F.pmod(pick, share).cast("int").alias("slot"))
    return low.join(top, ["study", "slot"]).select("study", "trial", "donor")


class AsyncHalving:
    """Promotions on reports in the order of their arrival.

    On each report of a rung step, from the top rung down: of the trials finished there the best
    floor(n / eta) may go on; the best one not promoted yet does.  Results that were not promoted lie in a heap; the rank of its
    first is one more than the number of better promoted ones.
    """

    def __init__(self, eta: int, steps: list[int]):
        self.eta, self.steps, self.made = eta, list(steps), 0
        self.waiting: list[list[tuple[float, int]]] = [[] for _ in steps]
        self.promoted: list[list[tuple[float, int]]] = [[] for _ in steps]
        self.seen: list[set[int]] = [set() for _ in steps]
        self.gone: list[set[int]] = [set() for _ in steps]

    def report(self, trial: int, step: int, value: float) -> list[tuple[int, int]]:
        """The promotions (trial, rung step) that follow: one at most.  Reports of other steps, repeated ones, and those of trials that were not asked to go so far, are ignored."""
        r = self.steps.index(step) if step in self.steps else -1
        if r < 0 or trial in self.seen[r] or r and trial not in self.gone[r - 1]:
            return []
        self.seen[r].add(trial)
        heapq.heappush(self.waiting[r], (-value, trial))
        for k in range(len(self.steps) - 2, -1, -1):
            n = len(self.waiting[k]) + len(self.promoted[k])
            if self.waiting[k] and bisect.bisect_left(self.promoted[k], self.waiting[k][0]) < n // self.eta:
                best = heapq.heappop(self.waiting[k])
                bisect.insort(self.promoted[k], best)
                self.gone[k].add(best[1])
                self.made += 1
                return [(best[1], self.steps[k])]
        return []

    def dump(self) -> dict:
        return {"eta": self.eta, "steps": self.steps, "made": self.made, "waiting": self.waiting, "promoted": self.promoted}

    @classmethod
    def load(cls, told: dict) -> AsyncHalving:
        own = cls(told["eta"], told["steps"])
        own.made = told["made"]
        own.waiting, own.promoted = ([[tuple(x) for x in rung] for rung in told[k]] for k in ("waiting", "promoted"))
        own.gone = [{t for _, t in rung} for rung in own.promoted]
        own.seen = [{t for _, t in rung} | gone for rung, gone in zip(own.waiting, own.gone)]
        return own


def async_halving(rows: list[tuple[int, int, float]], eta: int, steps: list[int]) -> list[tuple[int, int]]:
    """Reports (trial, step, value) in order of arrival -> promotions (trial, rung) in the order they are made."""
    own = AsyncHalving(eta, steps)
    return [x for r in rows for x in own.report(*r)]


def async_replay(reports: DataFrame, eta: int, steps: list[int]) -> DataFrame:
    """reports(study, ord, trial, step, value) -> (study, trial, rung, nth), one group per study, in the order of ``ord``; only reports at rung steps are gathered."""

    def one(group: pd.DataFrame) -> pd.DataFrame:
        g = group.sort_values("ord")
        made = async_halving(list(zip(g["trial"].tolist(), g["step"].tolist(), g["value"].tolist())), eta, steps)
        return pd.DataFrame([(g["study"].iloc[0], t, r, k) for k, (t, r) in enumerate(made)], columns=["study", "trial", "rung", "nth"])

    return reports.where(F.col("step").isin(steps)).groupBy("study").applyInPandas(one, "study string, trial long, rung long, nth long")
