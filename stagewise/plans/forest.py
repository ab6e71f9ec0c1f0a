"""Stage forests: from trials, from a plan with checkpoints, and their changes.

A stage is an interval of one node that every trial either trains wholly or not at all.  Cut
points of a node are the ends of the segments that stop there, the starts of its children, and checkpoints.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagewise.store import Scratch


def cut_points(segments: DataFrame) -> DataFrame:
    """(path, cut): start, ends of segments (children start at such ends) of each node; at most one row per node and step."""
    return segments.select("path", F.explode(F.array("start", "end")).alias("cut")).distinct()


def merge_trials(segments: DataFrame) -> DataFrame:
    """segments -> stages(path, lo, hi, parent_path, parent_hi, trials, cfg); shared prefixes are one stage.

    ``trials`` counts the segments that train the stage: those of its node that end at hi or later.
    """
    ends = segments.groupBy("path", "end").agg(F.count("*").alias("n"), F.min("start").alias("start"), F.min("parent").alias("parent"), F.min("cfg").alias("cfg"))
    # ends of a node are at most as many as its steps; a window over them has no unbounded group
    w = Window.partitionBy("path").orderBy("end")
    lo = F.coalesce(F.lag("end").over(w), F.col("start"))
    reach = F.sum("n").over(w.rowsBetween(0, Window.unboundedFollowing))
    first = F.lag("end").over(w).isNull()
    return ends.select(
        "path", lo.alias("lo"), F.col("end").alias("hi"),
        F.when(first, F.col("parent")).otherwise(F.col("path")).alias("parent_path"),
        F.when(first & F.col("parent").isNull(), None).otherwise(lo).alias("parent_hi"), reach.alias("trials"), "cfg",
    )


def insert_trials(stages: DataFrame, segments: DataFrame) -> DataFrame:
    """Stages(path, lo, hi, parent_path, parent_hi) after new trials came: existing stages are split where new segments end inside them.

    Only nodes on the new trials' paths are cut; all others pass through the left join unchanged.
    """
    new = segments.groupBy("path").agg(F.sort_array(F.collect_set("end")).alias("ends"), F.min("start").alias("start"), F.min("parent").alias("parent"))
    known = stages.groupBy("path").agg(F.max("hi").alias("reach"))
    begins = stages.groupBy("path").agg(F.min_by("parent_path", "lo").alias("up"), F.min("lo").alias("first"))
    begins = begins.unionByName(segments.select("path", F.col("parent").alias("up"), F.col("start").alias("first"))).groupBy("path").agg(F.min("up").alias("up"), F.min("first").alias("first"))
    inside = stages.join(new.select("path", "ends"), "path", "left")
    within = F.filter(F.coalesce("ends", F.array().cast("array<bigint>")), lambda x: (x > F.col("lo")) & (x < F.col("hi")))
    split = inside.select("path", "lo", "hi", within.alias("cuts")).select("path", F.explode(F.concat(F.array("lo"), "cuts")).alias("lo"), "hi", "cuts")
    old = split.select("path", "lo", F.coalesce(F.array_min(F.filter("cuts", lambda x: x > F.col("lo"))), F.col("hi")).alias("hi"))
    beyond = new.join(known, "path", "left").withColumn("reach", F.coalesce("reach", "start"))
    later = beyond.select("path", "reach", F.explode(F.filter("ends", lambda x: x > F.col("reach"))).alias("hi"), "ends")
    fresh = later.select("path", F.coalesce(F.array_max(F.filter("ends", lambda x: (x < F.col("hi")) & (x > F.col("reach")))), F.col("reach")).alias("lo"), "hi")
    # within a node a stage follows the one before it, the first one its parent's stage that ends there
    told = old.unionByName(fresh).join(begins, "path")
    own = F.col("lo") > F.col("first")
    return told.select(
        "path", "lo", "hi", F.when(own, F.col("path")).otherwise(F.col("up")).alias("parent_path"),
        F.when(own | F.col("up").isNotNull(), F.col("lo")).alias("parent_hi"),
    )


def drop_trials(segments: DataFrame, killed: DataFrame) -> DataFrame:
    """Stages without the killed(study, trial); a stage stays as long as any trial needs it."""
    return merge_trials(segments.join(killed, ["study", "trial"], "left_anti"))


def trials_of_stage(stages: DataFrame, segments: DataFrame) -> DataFrame:
    """(path, lo, hi, n_trials, min_trial, max_trial): an equi join on the node with a range condition."""
    s, g = stages.select("path", "lo", "hi"), segments.select(F.col("path").alias("p"), "start", "end", "trial")
    return s.join(g, (F.col("path") == F.col("p")) & (F.col("start") <= F.col("lo")) & (F.col("end") >= F.col("hi"))).groupBy("path", "lo", "hi").agg(
        F.count("*").alias("n_trials"), F.min("trial").alias("min_trial"), F.max("trial").alias("max_trial")
    )


def ancestry(lines: DataFrame) -> DataFrame:
    """lines(path, line) -> (node, ancestor, start, limit, dist): each node with itself and its ancestors.

    ``start`` is the ancestor's, ``limit`` the step up to which it is trained on the way to the node; null for the node itself.
    """
    n = F.size("line")
    at = F.explode(F.transform("line", lambda x, i: F.struct(
        x["path"].alias("ancestor"), x["start"].alias("start"), F.try_element_at("line", i + 2)["start"].alias("limit"), (n - 1 - i).cast("long").alias("dist")
    )))
    return lines.select(F.col("path").alias("node"), at.alias("x")).select("node", "x.*")


def resume_points(requests: DataFrame, ckpts: DataFrame, lines: DataFrame) -> DataFrame:
    """requests(path, step), ckpts(path, step), lines(path, line) -> (path, step, ckpt_path, ckpt_step, up): the nearest checkpoint on the way.

    The climb to ancestors is one explosion of the line; the pick is one aggregation: deepest
    node first, then largest step.  ``up`` is how many nodes above the request's it lies.  A request without any starts fresh (nulls).
    """
    asked = requests.select("path", "step").distinct()
    ways = ancestry(lines.join(asked.select("path").distinct(), "path", "left_semi")).join(asked.withColumnRenamed("path", "node"), "node")
    ways = ways.withColumn("limit", F.coalesce("limit", "step"))
    c = ckpts.select(F.col("path").alias("ancestor"), F.col("step").alias("at"))
    near = ways.join(c, "ancestor").where("at <= limit").groupBy("node", "step").agg(
        F.max(F.struct((-F.col("dist")).alias("up"), "at", "ancestor")).alias("b")
    )
    out = asked.alias("r").join(near.alias("n"), F.expr("r.path = n.node and r.step = n.step"), "left")
    return out.select("r.path", "r.step", F.col("b.ancestor").alias("ckpt_path"), F.col("b.at").alias("ckpt_step"), (-F.col("b.up")).alias("up"))


def climb(requests: DataFrame, ckpts: DataFrame, nodes: DataFrame) -> DataFrame:
    """:func:`resume_points` by parents(nodes(path, parent, start)) alone, a level a round, for plans whose ways are too long to be kept."""
    scratch = Scratch(requests.sparkSession, "climb")
    c = ckpts.select(F.col("path").alias("at"), F.col("step").alias("saved"))
    up = nodes.select(F.col("path").alias("at"), "parent", "start")
    asked = scratch.save(requests.select("path", "step").distinct(), "asked")
    front, found, k = asked.withColumns({"at": F.col("path"), "limit": F.col("step")}), [], 0
    while True:
        here = front.join(c, "at", "left").groupBy("path", "step", "at", "limit").agg(F.max(F.when(F.col("saved") <= F.col("limit"), F.col("saved"))).alias("saved"))
        here = scratch.save(here, f"here-{k}")
        found.append(here.where("saved is not null").select("path", "step", F.col("at").alias("ckpt_path"), F.col("saved").alias("ckpt_step"), F.lit(k).cast("long").alias("up")))
        k += 1
        front = scratch.save(here.where("saved is null").join(up, "at").where("parent is not null").select("path", "step", F.col("parent").alias("at"), F.col("start").alias("limit")), f"front-{k}")
        if front.isEmpty():
            return asked.join(reduce(DataFrame.unionByName, found), ["path", "step"], "left")


def needs(requests: DataFrame, ckpts: DataFrame, lines: DataFrame) -> DataFrame:
    """(path, lo, hi, node, step): what each request still has to train in each node on its way."""
    found = resume_points(requests, ckpts, lines)
    ways = ancestry(lines.join(found.select("path").distinct(), "path", "left_semi")).alias("a").join(found.alias("f"), F.expr("a.node = f.path"))
    hi = F.coalesce("limit", "step")
    lo = F.when(F.col("ancestor") == F.col("ckpt_path"), F.col("ckpt_step")).otherwise(F.col("start"))
    # ancestors above the checkpoint's node need nothing
    needed = F.col("up").isNull() | (F.col("dist") <= F.col("up"))
    return ways.where(needed).select(F.col("ancestor").alias("path"), lo.alias("lo"), hi.alias("hi"), F.col("node"), "step").where("lo < hi")


def from_plan(requests: DataFrame, ckpts: DataFrame, lines: DataFrame, mode: str = "breakpoints", running: DataFrame | None = None) -> DataFrame:
    """Stages that the open requests still need: (path, lo, hi, parent_path, parent_hi, resume_path, resume_step, blocked).

    ``breakpoints`` cuts each node at every end and resume point, so no step is trained twice; ``literal``
    gives one stage per need and repeats what several requests share between two checkpoints.
    A stage follows its parent stage, or else begins at a checkpoint (resume), or else at step 0.
    ``running``(path, lo, hi) are stages that workers hold now: what they train is not given out again, and a stage
    that would begin inside of one or at its end is blocked, and so is all that follows it, until its checkpoint is there.
    """
    need = needs(requests, ckpts, lines).select("path", "lo", "hi").distinct()
    if mode == "literal":
        spans = need
    else:
        cuts = need.select("path", F.explode(F.array("lo", "hi")).alias("cut"))
        if running is not None:
            cuts = cuts.unionByName(running.select("path", F.explode(F.array("lo", "hi")).alias("cut")).join(need.select("path").distinct(), "path", "left_semi"))
        # child starts and other requests inside a need are among the ends of needs of the same node
        w = Window.partitionBy("path").orderBy("cut")
        spans = cuts.distinct().select("path", F.col("cut").alias("lo"), F.lead("cut").over(w).alias("hi")).where("hi is not null")
        n = need.select(F.col("path").alias("p"), F.col("lo").alias("a"), F.col("hi").alias("b"))
        spans = spans.join(n, F.expr("path = p and a <= lo and hi <= b"), "left_semi")
    up = lines.select("path", F.element_at("line", -1)["start"].alias("start"), F.try_element_at("line", F.lit(-2))["path"].alias("up"))
    own = F.col("lo") > F.col("start")
    at = spans.join(up, "path").select("path", "lo", "hi", F.when(own, F.col("path")).otherwise(F.col("up")).alias("before"))
    saved = ckpts.select(F.col("path").alias("before"), F.col("step").alias("lo")).distinct().withColumn("saved", F.lit(True))
    at = at.join(saved, ["before", "lo"], "left").withColumn("saved", F.coalesce("saved", F.lit(False)))
    told = at.select(
        "path", "lo", "hi", F.when(~F.col("saved"), F.col("before")).alias("parent_path"), F.when(~F.col("saved") & F.col("before").isNotNull(), F.col("lo")).alias("parent_hi"),
        F.when(F.col("saved"), F.col("before")).alias("resume_path"), F.when(F.col("saved"), F.col("lo")).alias("resume_step"),
    )
    if running is None:
        return told.withColumn("blocked", F.lit(False))
    held = running.select(F.col("path").alias("p"), F.col("lo").alias("a"), F.col("hi").alias("b"))
    told = told.join(held, F.expr("path = p and a <= lo and hi <= b"), "left_anti")
    # what waits for a running stage has a parent that is not among the stages; what follows it waits with it
    waits = held.select(F.col("p").alias("parent_path"), F.col("b").alias("parent_hi")).distinct().withColumn("waits", F.lit(True))
    told = told.join(waits, ["parent_path", "parent_hi"], "left").withColumn("waits", F.coalesce("waits", F.lit(False)))
    behind = told.where("waits").select(F.col("path").alias("wp"), F.col("lo").alias("wl"))
    ways = ancestry(lines.join(told.select("path").distinct(), "path", "left_semi"))
    late = ways.join(behind, F.expr("ancestor = wp and (limit is null or wl < limit)")).groupBy(F.col("node").alias("bp")).agg(F.min(F.when(F.col("limit").isNull(), F.col("wl")).otherwise(F.lit(0))).alias("from"))
    told = told.join(late, F.expr("path = bp"), "left")
    return told.withColumn("blocked", F.coalesce(F.col("lo") >= F.col("from"), F.lit(False))).select("path", "lo", "hi", "parent_path", "parent_hi", "resume_path", "resume_step", "blocked")
