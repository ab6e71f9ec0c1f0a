"""Studies as clients run them: one model, one data set, some settings; any number of tuners one after the other.

Studies of one model, data set and set of settings share one plan, so what one of them has trained answers the others.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stagewise.functions import hpfunc as H
from stagewise.operators import tuners
from stagewise.operators.engine import Engine
from stagewise.plans import trials as T
from stagewise.store import PlanStore, shared_dir


def plan_key(model: str, dataset: str, hp_set: list[str], seed: int = 1) -> str:
    """The plan of all studies that could share steps: equal model, data set, settings and order of the data."""
    return hashlib.sha256("\0".join([model, dataset, *sorted(hp_set), str(seed)]).encode()).hexdigest()[:16]


def upto(segments: DataFrame, reached: DataFrame) -> DataFrame:
    """Segments cut at the step of reached(study, trial, step); other trials are left out."""
    known = segments.join(reached.select("study", "trial", F.col("step").alias("upto")), ["study", "trial"]).where("start < upto")
    return known.withColumn("end", F.least("end", "upto")).drop("upto").select(*T.SEGMENT)


class Study:
    """``engine`` trains; ``hp_set`` are the settings that are tuned."""

    def __init__(self, engine: Engine, name: str, hp_set: list[str]):
        self.engine, self.name, self.hp_set = engine, name, sorted(hp_set)

    @classmethod
    def open(cls, spark: SparkSession, name: str, model: type, dataset: str, hp_set: list[str], data, held: DataFrame, classes: int, root: str | None = None, **options) -> Study:
        """A study on the plan of its kind under ``root``, which is made if it is not there yet."""
        store = PlanStore(spark, root or f"{shared_dir(spark)}/plans", plan_key(model.__name__, dataset, hp_set, options.get("seed", 1)))
        return cls(Engine(store, data, held, classes, model=model, **options), name, hp_set)

    def trials(self, families: dict[str, list], where=None) -> DataFrame:
        """The trials of a grid as segments."""
        from stagewise.functions.space import grid

        if sorted(families) != self.hp_set:
            raise ValueError(f"the study tunes {self.hp_set}, the space has {sorted(families)}")
        return T.canonical(grid(self.engine.spark, self.name, families, where))

    def ask(self, segments: DataFrame, reached: DataFrame, wait: str = "all") -> DataFrame:
        """Has trials trained up to the steps of reached(study, trial, step): (study, trial, step, value) of the answered ones.

        ``wait``: for all of them, or for any.
        """
        cut = self.engine.scratch.save(upto(segments, reached), f"cut-{self.engine.submissions}")
        self.engine.submit(cut)
        self.engine.run(wait)
        return self.engine.results(cut)

    def tune(self, tuner, segments: DataFrame) -> DataFrame:
        """Runs a tuner to its end: (study, trial, rung, rank, action, value)."""
        return tuner(self, segments)

    def evaluate(self, families: dict[str, list[H.Piece]], step: int) -> float:
        """The value of one configuration, given as one function list per setting, at a step."""
        one = self.trials({k: [v] for k, v in families.items()})
        reached = one.select("study", "trial").distinct().withColumn("step", F.lit(step).cast("long"))
        return self.ask(one, reached).first()["value"]

    def finish(self, segments: DataFrame, decisions: DataFrame, extra: int) -> DataFrame:
        """Trains the best trial of a tuner's last rung ``extra`` steps more, under its last configuration."""
        best = decisions.orderBy(F.desc("rung"), F.desc("value"), "study", "trial").limit(1).select("study", "trial", F.col("rung").alias("at"))
        own = segments.join(F.broadcast(best), ["study", "trial"]).where("start < at").withColumn("end", F.least("end", "at"))
        last = F.max("end").over(Window.partitionBy("study", "trial"))
        longer = own.withColumn("end", F.when(F.col("end") == last, F.col("end") + extra).otherwise(F.col("end")))
        reached = longer.groupBy("study", "trial").agg(F.max("end").alias("step"))
        return self.ask(longer.select(*T.SEGMENT), reached)


def _at(segments: DataFrame, step) -> DataFrame:
    """(study, trial, step): all trials to a step, or to their own end if it comes before."""
    return segments.groupBy("study", "trial").agg(F.least(F.max("end"), F.lit(step).cast("long")).alias("step"))


def _ranked(told: DataFrame, rung: int, kept) -> DataFrame:
    """Decisions on one rung: the first ``kept`` of each study, by value and then trial, go on."""
    w = Window.partitionBy("study").orderBy(F.desc("value"), "trial")
    n = F.count("*").over(Window.partitionBy("study"))
    out = told.withColumns({"rank": F.row_number().over(w).cast("long"), "n": n})
    action = F.when(F.col("rank") <= kept(F.col("n")), "promote").otherwise("stop")
    return out.select("study", "trial", F.lit(rung).cast("long").alias("rung"), "rank", action.alias("action"), "value")


def _rungs(study: Study, segments: DataFrame, steps: list[int], kepts: list, tag: str) -> DataFrame:
    """A barrier after each rung; the trials that go on resume from their checkpoints."""
    alive, out = segments, None
    for k, (step, kept) in enumerate(zip(steps, kepts)):
        told = _ranked(study.ask(alive, _at(alive, step)), step, kept)
        if k == len(steps) - 1:
            told = told.withColumn("action", F.lit("finish"))
        told = study.engine.scratch.save(told, f"{tag}-{k}-{study.engine.submissions}")
        out = told if out is None else out.unionByName(told)
        alive = segments.join(told.where("action = 'promote'").select("study", "trial"), ["study", "trial"], "left_semi")
    return out


def grid(most: int):
    """All trials to the end."""
    return lambda study, segments: _rungs(study, segments, [most], [lambda n: n], "grid")


def sampled(n: int, most: int, seed: int = 1):
    """A random subset of the trials to the end, in an order that any engine repeats."""
    from stagewise.functions.space import sample

    def run(study: Study, segments: DataFrame) -> DataFrame:
        own = sample(segments.select("study", "trial").distinct(), n, seed)
        return study.tune(grid(most), segments.join(F.broadcast(own), ["study", "trial"], "left_semi"))

    return run


def adaptive(rounds: int, k: int, at: int, most: int, factors: tuple[float, float] = (0.5, 1.5), hp: str = "lr", seed: int = 1):
    """Proposals near the best so far: in each round the ``k`` best trials get a successor with another value of ``hp`` from step ``at`` on.

    A successor shares its model's beginning, so only its tail is trained.
    """

    def run(study: Study, segments: DataFrame) -> DataFrame:
        now, out = segments, None
        for r in range(rounds):
            told = study.engine.scratch.save(_ranked(study.ask(now, _at(now, most)), most, lambda n: F.lit(k)).withColumn("round", F.lit(r)), f"adaptive-{r}-{study.engine.submissions}")
            out = told if out is None else out.unionByName(told)
            best = out.withColumn("place", F.row_number().over(Window.partitionBy("study").orderBy(F.desc("value"), "trial"))).where(F.col("place") <= k)
            first = segments.agg(F.max("trial")).first()[0] + 1 + r * k
            pairs = study.engine.scratch.save(best.select("study", (F.lit(first) + F.col("place") - 1).cast("long").alias("trial"), F.col("trial").alias("donor")), f"proposed-{r}-{study.engine.submissions}")
            made = forked(now if r == 0 else known, pairs, at, hp, factors, seed + r).join(pairs.select("study", "trial"), ["study", "trial"], "left_semi")
            now = study.engine.scratch.save(made.select(*T.SEGMENT), f"proposals-{r}-{study.engine.submissions}")
            known = segments.unionByName(now) if r == 0 else known.unionByName(now)
        return out

    return run


def halving(eta: int, least: int, most: int):
    """Synchronous halving: of the trials at a rung the best floor(n / eta), one at least, go on."""
    steps = tuners.rungs(eta, least, most)
    return lambda study, segments: _rungs(study, segments, steps, [lambda n: F.greatest(F.floor(n / eta), F.lit(1))] * len(steps), "halving")


def milestones(schedule: list[tuple[int, int]]):
    """(step, survivors) in turn."""
    return lambda study, segments: _rungs(study, segments, [s for s, _ in schedule], [(lambda n, k=k: F.lit(k)) for _, k in schedule], "milestones")


def hyperband(eta: int, least: int, most: int, seed: int = 1):
    """Brackets of halving, each on trials of its own in a seeded order; prefixes are shared between brackets through the plan."""

    def run(study: Study, segments: DataFrame) -> DataFrame:
        order = F.md5(F.concat(F.lit(f"{seed}-"), "study", F.lit("-"), F.col("trial").cast("string")))
        place = Window.partitionBy("study").orderBy(order, "trial")
        placed = segments.select("study", "trial").distinct().withColumn("place", F.row_number().over(place))
        out, begin = None, 0
        for b in tuners.hyperband(eta, least, most):
            own = placed.where((F.col("place") > begin) & (F.col("place") <= begin + b["trials"])).select("study", "trial")
            begin += b["trials"]
            told = study.tune(halving(eta, b["first_step"], most), segments.join(own, ["study", "trial"], "left_semi")).withColumn("bracket", F.lit(b["bracket"]))
            out = told if out is None else out.unionByName(told)
        return out

    return run


def async_halving(eta: int, least: int, most: int):
    """Asynchronous halving: whenever any results are there, promotions follow at once; nothing waits for a whole rung.

    Results that come in one round are reported in the order of their trials.
    """
    steps = tuners.rungs(eta, least, most)

    def run(study: Study, segments: DataFrame) -> DataFrame:
        spark = study.engine.spark
        # a client's trials: their numbers and values are held here, as in any client
        own, made, seen = {}, [], set()
        reached = _at(segments, steps[0])
        while True:
            told = study.ask(segments, reached, "any").orderBy("study", "step", "trial").collect()
            for r in told:
                if (r.study, r.trial, r.step) not in seen:
                    seen.add((r.study, r.trial, r.step))
                    tuner = own.setdefault(r.study, tuners.AsyncHalving(eta, steps))
                    made += [(r.study, t, s, len(made) + k, r.value) for k, (t, s) in enumerate(tuner.report(r.trial, r.step, r.value))]
            up = dict(zip(steps, steps[1:]))
            asked = {(s, t): steps[0] for s, t in map(tuple, reached.select("study", "trial").collect())} | {(s, t): up[r] for s, t, r, *_ in made}
            reached = spark.createDataFrame([(s, t, r) for (s, t), r in asked.items()], "study string, trial bigint, step bigint")
            if study.engine.open_requests().isEmpty() and all((s, t, r) in seen for (s, t), r in asked.items()):
                break
        return spark.createDataFrame([(s, t, r, k, "promote", v) for s, t, r, k, v in made], "study string, trial bigint, rung bigint, rank bigint, action string, value double")

    return run


def median_stop(every: int, most: int, grace: int, cohort: int = 3):
    """Trials report each ``every`` steps; one whose best so far is below the median of the others' means stops there."""

    def run(study: Study, segments: DataFrame) -> DataFrame:
        alive, out = segments, None
        history = None
        for step in range(every, most + 1, every):
            told = study.engine.scratch.save(study.ask(alive, _at(alive, step)).withColumn("step", F.lit(step).cast("long")), f"median-{step}-{study.engine.submissions}")
            history = told if history is None else history.unionByName(told)
            bad = tuners.median_stop(history, grace, cohort).where(F.col("stop_at") == step).select("study", "trial", F.lit(True).alias("bad"))
            last = F.lit(step + every > most)
            now = told.join(bad, ["study", "trial"], "left").withColumn("action", F.when(last, "finish").when(F.col("bad"), "stop").otherwise("promote"))
            w = Window.partitionBy("study").orderBy(F.desc("value"), "trial")
            now = now.select("study", "trial", F.lit(step).cast("long").alias("rung"), F.row_number().over(w).cast("long").alias("rank"), "action", "value")
            now = study.engine.scratch.save(now, f"median-now-{step}-{study.engine.submissions}")
            out = now if out is None else out.unionByName(now)
            alive = segments.join(now.where("action = 'promote'").select("study", "trial"), ["study", "trial"], "left_semi")
        return out

    return run


def population(interval: int, most: int, quantile: float = 0.2, factors: tuple[float, float] = (0.8, 1.2), hp: str = "lr", seed: int = 1):
    """Population training: every interval the worst copy a donor of the best and go on with its setting ``hp`` changed.

    A copy is the donor's segments up to now and then a changed configuration: a fork in the plan, from the donor's checkpoint.
    """

    def run(study: Study, segments: DataFrame) -> DataFrame:
        now, out = segments, None
        for step in range(interval, most + 1, interval):
            told = study.ask(now, _at(now, step))
            w = Window.partitionBy("study").orderBy(F.desc("value"), "trial")
            told = told.select("study", "trial", F.lit(step).cast("long").alias("step"), "value", F.row_number().over(w).cast("long").alias("rank"))
            told = study.engine.scratch.save(told, f"population-{step}-{study.engine.submissions}")
            pairs = tuners.population(told, step, quantile, seed) if step < most else told.limit(0).select("study", "trial", F.col("trial").alias("donor"))
            pairs = study.engine.scratch.save(pairs, f"pairs-{step}-{study.engine.submissions}")
            row = told.join(pairs, ["study", "trial"], "left").select("study", "trial", F.col("step").alias("rung"), "rank", F.when(F.col("donor").isNotNull(), "fork").when(F.lit(step == most), "finish").otherwise("promote").alias("action"), "value", "donor")
            out = row if out is None else out.unionByName(row)
            now = study.engine.scratch.save(forked(now, pairs, step, hp, factors, seed), f"now-{step}-{study.engine.submissions}")
        return out

    return run


def forked(segments: DataFrame, pairs: DataFrame, step: int, hp: str, factors: tuple[float, float], seed: int) -> DataFrame:
    """Segments after an exploit step: each trial of pairs(study, trial, donor) has its donor's segments up to ``step`` and then the donor's configuration with another value of ``hp``.

    Only a constant setting is changed; the factor is one of two, by a digest of seed, trial and step.
    """
    stay = segments.join(pairs.select("study", "trial"), ["study", "trial"], "left_anti").select("study", "trial", F.col("start").alias("ord"), "cfg", (F.col("end") - F.col("start")).alias("steps"))
    own = segments.withColumnRenamed("trial", "donor").join(pairs, ["study", "donor"])
    before = own.where(F.col("start") < step).select("study", "trial", F.col("start").alias("ord"), "cfg", (F.least("end", F.lit(step)) - F.col("start")).alias("steps"))
    after = own.where(F.col("end") > step)
    up = F.substring(F.md5(F.concat(F.lit(f"{seed}-{step}-"), F.col("trial").cast("string"))), 1, 1).isin(*"01234567")
    old = F.regexp_extract("cfg", rf"(?:^|;){hp}=constant\(([^)]*)\)", 1)
    new = F.round(old.cast("double") * F.when(up, factors[1]).otherwise(factors[0]), 12).cast("string")
    text = F.when(old == "", F.col("cfg")).otherwise(F.replace("cfg", F.concat(F.lit(f"{hp}=constant("), old, F.lit(")")), F.concat(F.lit(f"{hp}=constant("), new, F.lit(")"))))
    after = after.select("study", "trial", F.greatest("start", F.lit(step)).alias("ord"), text.alias("cfg"), (F.col("end") - F.greatest("start", F.lit(step))).alias("steps"))
    return T.canonical(stay.unionByName(before).unionByName(after))
