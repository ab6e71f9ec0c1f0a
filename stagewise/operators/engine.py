"""The loop of a plan: submit, derive a tree, place chains, train, report, until nothing is open.

The plan's tables (:mod:`stagewise.store`) are the only state.  Each round derives a new tree from them, gives its
costliest ready chains to the workers and forgets the tree; checkpoints and reports are appended.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.operators import training
from stagewise.plans import forest, schedule
from stagewise.plans import trials as T
from stagewise.plans.plan import trial_requests, unneeded
from stagewise.store import PlanStore, Scratch


@dataclass
class Round:
    number: int
    chains: int
    stages: int
    steps: int
    open: int


class Engine:
    """A plan, its training data and a number of workers.

    A later submission that leaves a node where no checkpoint is trains from the last one before it again; checkpoints at
    every ``every`` steps bound what is repeated.
    """

    def __init__(
        self, store: PlanStore, data: tuple[np.ndarray, np.ndarray], held: DataFrame, classes: int, workers: int = 40,
        model: type = training.Softmax, measure: str = "value", seed: int = 1, iteration: int = 1, every: int | None = None,
    ):
        self.store, self.data, self.held, self.classes = store, data, held, classes
        self.workers, self.model, self.measure, self.seed, self.iteration, self.every = workers, model, measure, seed, iteration, every
        self.spark = store.spark
        self.scratch = Scratch(self.spark, "engine")
        self.name = uuid.uuid4().hex[:12]  # parts of several engines on one plan never meet
        self.rounds: list[Round] = []
        self.submissions = 0

    def submit(self, segments: DataFrame) -> tuple[int, int]:
        """Adds what the plan lacks of some trials, many at once: (requests that it could answer at once, new requests)."""
        self.submissions += 1
        part = f"{self.name}-submission-{self.submissions}"
        segments = self.scratch.save(segments, f"segments-{self.submissions}")
        asked = self.scratch.save(trial_requests(segments), f"asked-{self.submissions}")
        wanted = asked.select("path", "step").distinct()
        answered = wanted.join(self.store.read("metrics").select("path", "step"), ["path", "step"], "left_semi").count()
        new = T.nodes(segments).select("path", "parent", "start", "cfg", "depth").join(self.store.read("nodes").select("path"), "path", "left_anti")
        fresh = self.scratch.save(wanted.join(self.store.read("requests"), ["path", "step"], "left_anti"), f"fresh-{self.submissions}")
        self.store.append("nodes", new.join(T.lines(segments), "path"), part)
        self.store.append("asked", asked, part)
        self.store.append("requests", fresh, part)
        return answered, fresh.count()

    def open_requests(self) -> DataFrame:
        return self.store.read("requests").distinct().join(self.store.read("metrics").select("path", "step"), ["path", "step"], "left_anti")

    def tree(self, running: DataFrame | None = None) -> DataFrame:
        """The stages that open requests need now, with cost, start and configuration."""
        nodes, ckpts = self.store.read("nodes"), self.store.read("ckpts").select("path", "step")
        stages = forest.from_plan(self.open_requests(), ckpts, nodes.select("path", "line"), running=running)
        seconds = self.store.read("profile")
        told = stages.join(nodes.select("path", "start", "cfg"), "path")
        return schedule.costs(told, seconds if self.store.parts("profile") else None)

    def round(self) -> Round | None:
        """One stateless round; None when no request is open."""
        n = len(self.rounds)
        stages = self.scratch.save(self.tree(), f"tree-{n}")
        if stages.isEmpty():
            return None
        chosen = schedule.round(stages, self.store.read("nodes").select("path", "line"), self.workers)
        chosen = chosen.join(stages.select("path", "lo", "hi", "start", "cfg"), ["path", "lo", "hi"])
        saved = self.store.read("ckpts").select(F.col("path").alias("resume_path"), F.col("step").alias("resume_step"), "ckpt")
        placed = self.scratch.save(chosen.join(saved, ["resume_path", "resume_step"], "left"), f"placed-{n}")
        done = training.run_chains(placed, self.data, self.classes, self.model, self.seed, self.iteration, self.every)
        self.store.append("ckpts", done, f"{self.name}-round-{n}")
        self.report(n)
        told = placed.agg(F.countDistinct("leaf"), F.count("*"), F.sum(F.col("hi") - F.col("lo"))).first()
        self.scratch.drop(f"tree-{n}", f"placed-{n}")
        self.rounds.append(Round(n, told[0], told[1], told[2], self.open_requests().count()))
        return self.rounds[-1]

    def report(self, number: int) -> None:
        """Evaluates the checkpoints that open requests wait for, and appends the metrics."""
        ready = self.store.read("ckpts").join(self.open_requests(), ["path", "step"], "left_semi")
        models = ready.select(F.col("path").alias("study"), F.col("step").alias("trial"), "ckpt")
        told = training.scores(models, self.held, self.model).select(F.col("study").alias("path"), F.col("trial").alias("step"), F.col(self.measure).alias("value"))
        self.store.append("metrics", told, f"{self.name}-round-{number}")

    def run(self, wait: str = "all") -> list[Round]:
        """Rounds until no request is open (``all``) or until some request of this call is answered (``any``)."""
        out: list[Round] = []
        before = None
        while (r := self.round()) is not None:
            out.append(r)
            if wait == "any" and before is not None and r.open < before or wait == "any" and before is None and r.open == 0:
                break
            before = r.open if before is None else before
            if r.open == 0:
                break
        return out

    def results(self, segments: DataFrame) -> DataFrame:
        """(study, trial, step, value) of the answered requests of some trials."""
        return trial_requests(segments).join(self.store.read("metrics").dropDuplicates(["path", "step"]), ["path", "step"]).select("study", "trial", "step", "value")

    def checkpoints(self, segments: DataFrame) -> DataFrame:
        """(study, trial, step, ckpt) where the trials end."""
        return trial_requests(segments).join(self.store.read("ckpts").dropDuplicates(["path", "step"]), ["path", "step"]).select("study", "trial", "step", "ckpt")

    def kill(self, killed: DataFrame) -> DataFrame:
        """The checkpoints(path, step) that the plan no longer needs without the killed(study, trial); requests of those trials alone are closed.

        Facts are never taken back: a closed request has a metric of null.
        """
        asked = self.store.read("asked").distinct()
        alone = asked.join(killed, ["study", "trial"], "left_semi").select("path", "step").distinct()
        alone = alone.join(asked.join(killed, ["study", "trial"], "left_anti"), ["path", "step"], "left_anti").join(self.open_requests(), ["path", "step"], "left_semi")
        self.store.append("metrics", self.scratch.save(alone.withColumn("value", F.lit(None).cast("double")), f"killed-{self.store.parts('metrics')}"), f"{self.name}-killed-{self.store.parts('metrics')}")
        return unneeded(self.store.read("ckpts").select("path", "step"), asked, self.store.read("nodes").select("path", "line"), killed)

    def profile(self, seconds: DataFrame) -> None:
        """Seconds per step by configuration(cfg, sec), measured beforehand."""
        self.store.append("profile", seconds, f"{self.name}-profile-{self.store.parts('profile')}")
