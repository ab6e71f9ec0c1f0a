"""Costs, critical paths and chains of a stage forest.

Repeatedly taking the longest remaining path equals electing, for every stage, the leaf
with the costliest path through it, and grouping stages by their elected leaf.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagewise.store import Scratch


#: Rows of a table of seconds up to which it is broadcast (one row a configuration, some 40 bytes).
FEW_ROWS = 100_000


def costs(stages: DataFrame, seconds: DataFrame | None = None) -> DataFrame:
    """stages(.., lo, hi, cfg) with ``cost``: steps times seconds(cfg, sec) per step of the node's configuration; the mean where unknown."""
    steps = (F.col("hi") - F.col("lo")).cast("double")
    if seconds is None:
        return stages.withColumn("cost", steps)
    known = F.broadcast(seconds) if seconds.limit(FEW_ROWS + 1).count() <= FEW_ROWS else seconds
    mean = F.broadcast(seconds.agg(F.avg("sec").alias("mean_sec")))  # one row
    out = stages.join(known, "cfg", "left").crossJoin(mean).withColumn("cost", steps * F.coalesce("sec", "mean_sec"))
    return out.select(*stages.columns, "cost")


def stage_id(path: F.Column, hi: F.Column) -> F.Column:
    return F.concat(path, F.lit("@"), hi.cast("string"))


def leaf_paths(stages: DataFrame, lines: DataFrame) -> DataFrame:
    """stages(path, lo, hi, parent_path, parent_hi, cost), lines(path, line) -> (leaf, total, stage, path, lo, hi, cost): each stage of the path of each leaf.

    A leaf is a stage that no stage follows.  Its path is in its node's line: the stages of each
    ancestor up to the step at which the line leaves it.
    """
    from stagewise.plans.forest import ancestry

    s = stages.withColumn("stage", stage_id(F.col("path"), F.col("hi")))
    followed = s.where("parent_path is not null").select(stage_id(F.col("parent_path"), F.col("parent_hi")).alias("stage")).distinct()
    leaves = s.join(followed, "stage", "left_anti").select(F.col("stage").alias("leaf"), F.col("path").alias("node"), F.col("hi").alias("leaf_hi"))
    ways = leaves.join(ancestry(lines.join(leaves.select(F.col("node").alias("path")).distinct(), "path", "left_semi")).drop("start"), "node")
    on = F.expr("ancestor = path and hi <= coalesce(limit, leaf_hi)")
    rows = ways.join(s.select("stage", "path", "lo", "hi", "cost", "parent_path"), on)
    own = Window.partitionBy("leaf")  # as many rows as a path has stages
    # what lies before the last beginning, at a checkpoint or at step 0, is of another tree
    rows = rows.withColumn("begin", F.max(F.when(F.col("parent_path").isNull(), F.col("lo"))).over(own)).where("lo >= begin")
    return rows.withColumn("total", F.sum("cost").over(own)).select("leaf", "total", "stage", "path", "lo", "hi", "cost")


def chains(stages: DataFrame, lines: DataFrame | None = None) -> DataFrame:
    """(leaf, cost, n_stages, lo): one chain per leaf; a tie goes to the smaller leaf.  Without ``lines`` the leaves are elected level by level."""
    elected = elected_by_levels(stages) if lines is None else elected_leaves(stages, lines)
    per = elected.groupBy("leaf").agg(F.sum("cost").alias("cost"), F.count("*").alias("n_stages"), F.min("lo").alias("lo"))
    return per


def elected_leaves(stages: DataFrame, lines: DataFrame) -> DataFrame:
    """(stage, path, lo, hi, cost, leaf): the leaf whose whole path costs most among those below a stage."""
    paths = leaf_paths(stages, lines)
    best = F.min_by("leaf", F.struct(-F.col("total"), F.col("leaf"))).alias("leaf")
    return paths.groupBy("stage").agg(F.first("path").alias("path"), F.min("lo").alias("lo"), F.min("hi").alias("hi"), F.min("cost").alias("cost"), best)


def elected_by_levels(stages: DataFrame) -> DataFrame:
    """:func:`elected_leaves` from the leaves upwards, a level of stages a round: for forests whose paths are too long to be written out.

    The rows moved in all rounds are as many as there are stages; a round is a job, so shallow forests are quicker by paths.
    """
    scratch = Scratch(stages.sparkSession, "levels")
    up = F.when(F.col("parent_path").isNotNull(), stage_id(F.col("parent_path"), F.col("parent_hi"))).alias("up")
    s = scratch.save(stages.select(stage_id(F.col("path"), F.col("hi")).alias("stage"), up, "path", "lo", "hi", "cost"), "stages")
    # a parent that is not among the stages has been trained already
    children = s.where("up is not null").groupBy("up").agg(F.count("*").alias("n")).join(s.select(F.col("stage").alias("up")), "up", "left_semi")
    open_ = scratch.save(s.join(children.withColumnRenamed("up", "stage"), "stage"), "open-0")
    leaves = s.join(children.select(F.col("up").alias("stage")), "stage", "left_anti")
    done = scratch.save(leaves.withColumns({"leaf": F.col("stage"), "below": F.col("cost")}), "done-0")
    parts, waiting, k = [done], done, 0
    while not open_.isEmpty():
        k += 1
        told = waiting.groupBy(F.col("up").alias("stage")).agg(F.count("*").alias("ready"), F.min_by(F.struct("leaf", "below"), F.struct(-F.col("below"), F.col("leaf"))).alias("best"))
        now = open_.join(told, "stage").where("ready = n")
        done = scratch.save(now.select("stage", "up", "path", "lo", "hi", "cost", F.col("best.leaf").alias("leaf"), (F.col("best.below") + F.col("cost")).alias("below")), f"done-{k}")
        parts.append(done)
        open_ = scratch.save(open_.join(done.select("stage"), "stage", "left_anti"), f"open-{k}")
        # those whose parent is still open wait for their siblings
        waiting = scratch.save(waiting.unionByName(done).join(open_.select(F.col("stage").alias("up")), "up", "left_semi"), f"waiting-{k}")
    return reduce(DataFrame.unionByName, parts).select("stage", "path", "lo", "hi", "cost", "leaf")


def critical_path(stages: DataFrame, lines: DataFrame) -> DataFrame:
    """(leaf, total) of the costliest path."""
    return leaf_paths(stages, lines).groupBy("leaf").agg(F.max("total").alias("total")).orderBy(F.desc("total"), "leaf").limit(1)


def top_chains(stages: DataFrame, lines: DataFrame, idle: int) -> DataFrame:
    """The chains for the idle workers, costliest first."""
    return chains(stages, lines).orderBy(F.desc("cost"), "leaf").limit(idle)


def round(stages: DataFrame, lines: DataFrame, idle: int) -> DataFrame:
    """One stateless round over stages of a plan: (leaf, place, path, lo, hi, resume_path, resume_step) of the chains that idle workers take.

    A chain can be taken when its first stage begins at a checkpoint or at step 0 and is not blocked; the costliest go first.
    """
    own = elected_leaves(stages, lines).join(stages.select("path", "lo", "hi", "parent_path", "resume_path", "resume_step", "blocked"), ["path", "lo", "hi"])
    head = F.min_by(F.struct(F.col("parent_path").isNull().alias("free"), "blocked"), "lo").alias("head")
    able = own.groupBy("leaf").agg(F.sum("cost").alias("total"), head).where("head.free and not head.blocked")
    taken = F.broadcast(able.orderBy(F.desc("total"), "leaf").limit(idle).select("leaf"))  # a row a worker
    return own.join(taken, "leaf").select("leaf", "stage", "path", "lo", "hi", "cost", "resume_path", "resume_step")


def breadth_first(stages: DataFrame, depths: DataFrame) -> DataFrame:
    """Stages level by level: (path, lo, hi, depth) in the order (depth, lo, path), the rejected alternative; depths(path, depth).

    The order is a sort, not a global row number: consumers read it in order.
    """
    return stages.select("path", "lo", "hi").join(depths.select("path", F.col("depth").cast("long").alias("depth")), "path").orderBy("depth", "lo", "path")
