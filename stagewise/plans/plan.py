"""The durable search plan: nodes, requests, checkpoints and metrics as append-only facts.

Submission compares by anti and semi joins on node identity; nodes are never split.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.plans import trials as T
from stagewise.plans.forest import ancestry


@dataclass
class Submission:
    new_nodes: DataFrame
    new_requests: DataFrame
    answered: DataFrame
    trial_requests: DataFrame


def plan_nodes(segments: DataFrame) -> DataFrame:
    return T.nodes(segments).select("path", "parent", "start", "cfg", "depth")


def requests(segments: DataFrame) -> DataFrame:
    """(path, step, refs): the last node and step of each trial; trials that ask the same share a row."""
    return trial_requests(segments).groupBy("path", "step").agg(F.count("*").alias("refs"))


def trial_requests(segments: DataFrame) -> DataFrame:
    last = segments.groupBy("study", "trial").agg(F.max(F.struct("end", "path")).alias("last"))
    return last.select("study", "trial", F.col("last.path").alias("path"), F.col("last.end").alias("step"))


@dataclass
class Plan:
    """known nodes(path), requests(path, step), metrics(path, step, ..); all immutable DataFrames."""

    nodes: DataFrame
    asked: DataFrame
    metrics: DataFrame | None = None

    def submit(self, segments: DataFrame) -> Submission:
        wanted = trial_requests(segments)
        distinct = wanted.select("path", "step").distinct()
        answered = distinct.limit(0) if self.metrics is None else distinct.join(self.metrics.select("path", "step"), ["path", "step"], "left_semi")
        open_ = distinct if self.metrics is None else distinct.join(self.metrics.select("path", "step"), ["path", "step"], "left_anti")
        return Submission(
            plan_nodes(segments).join(self.nodes, "path", "left_anti"),
            open_.join(self.asked, ["path", "step"], "left_anti"),
            answered,
            wanted,
        )

    def record(self, s: Submission) -> Plan:
        """The plan after a submission; facts are only added."""
        return Plan(self.nodes.unionByName(s.new_nodes.select(self.nodes.columns)), self.asked.unionByName(s.new_requests), self.metrics)

    def release(self, segments: DataFrame, killed: DataFrame) -> DataFrame:
        """Requests that no trial but the killed ones asks for."""
        alive = trial_requests(segments.join(killed, ["study", "trial"], "left_anti")).select("path", "step")
        return self.asked.join(alive, ["path", "step"], "left_anti")


def unneeded(ckpts: DataFrame, asked: DataFrame, lines: DataFrame, killed: DataFrame) -> DataFrame:
    """ckpts(path, step) that no request of a trial outside of killed(study, trial) could resume from; asked(study, trial, path, step)."""
    alive = asked.join(killed, ["study", "trial"], "left_anti").select("path", "step").distinct()
    ways = ancestry(lines.join(alive.select("path").distinct(), "path", "left_semi"))
    needed = ways.join(alive.withColumnRenamed("path", "node"), "node").select(F.col("ancestor").alias("path"), F.coalesce("limit", "step").alias("upto"))
    reach = needed.groupBy("path").agg(F.max("upto").alias("upto"))
    return ckpts.join(reach, "path", "left").where("upto is null or step > upto").select(*ckpts.columns)


def empty_plan(segments: DataFrame) -> Plan:
    return Plan(plan_nodes(segments).select("path").limit(0), trial_requests(segments).select("path", "step").limit(0))
