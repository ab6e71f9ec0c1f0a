"""Canonical segments: neighbouring equal pieces joined, step ranges, lineage.

One shuffle by trial; everything else is row-local on the trial's array of pieces, so
the lineage costs no window and no self join.  A node is known by a digest chained over the
starts and configurations on the way to it, so keys have one size however deep a trial is.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_SEGMENT = "array<struct<k:int,start:bigint,end:bigint,cfg:string,path:string,parent:string,root:string>>"
DIGITS = 32  # hexadecimal digits of a digest that are kept: 128 bits
#: Columns of a segment.
SEGMENT = ["study", "trial", "k", "start", "end", "cfg", "path", "parent", "root", "depth"]


def chained(parent: Column, start: Column, cfg: Column) -> Column:
    """The identity of a node from its parent's (null: none), its start and its configuration (null is one of its own).

    The configuration's length is part of the digested text, so that no two lists of configurations read alike.
    """
    own = F.when(cfg.isNull(), F.lit("-")).otherwise(F.concat(F.length(cfg).cast("string"), F.lit(":"), cfg))
    return F.substring(F.sha2(F.concat(F.coalesce(parent, F.lit("")), F.lit("|"), start.cast("string"), F.lit("|"), own).cast("binary"), 256), 1, DIGITS)


def identity(*steps: tuple[int, str | None]) -> str:
    """The same for a client: (start, configuration) of each node on the way."""
    path = ""
    for start, cfg in steps:
        own = "-" if cfg is None else f"{len(cfg)}:{cfg}"
        path = hashlib.sha256(f"{path}|{start}|{own}".encode()).hexdigest()[:DIGITS]
    return path


def canonical(pieces: DataFrame) -> DataFrame:
    """pieces(study, trial, ord, cfg, steps) -> segments(study, trial, k, start, end, cfg, path, parent, root, depth).

    Pieces without steps vanish; equal neighbours are one segment.  ``path`` is the
    identity of the plan node a segment belongs to, given by the starts and configurations of all segments so far,
    but not the segment's own length; ``parent`` and ``root`` are those of the segment before and of the first.
    A null configuration differs from an empty one.  A trial without steps has no segments.
    """
    per_trial = pieces.where("steps > 0").groupBy("study", "trial").agg(F.array_sort(F.collect_list(F.struct("ord", "cfg", "steps"))).alias("p"))
    empty = F.expr(f"cast(array() as {_SEGMENT})")

    def add(done: Column, piece: Column) -> Column:
        old = F.try_element_at(done, F.lit(-1))
        same = (F.size(done) > 0) & old["cfg"].eqNullSafe(piece["cfg"])
        start = F.coalesce(old["end"], F.lit(0).cast("long"))
        names = ("k", "start", "end", "cfg", "path", "parent", "root")
        longer = F.struct(*[(old["end"] + piece["steps"] if n == "end" else old[n]).alias(n) for n in names])
        own = chained(old["path"], start, piece["cfg"])
        new = F.struct(
            F.size(done).alias("k"), start.alias("start"), (start + piece["steps"]).alias("end"), piece["cfg"].alias("cfg"),
            own.alias("path"), old["path"].alias("parent"), F.coalesce(old["root"], own).alias("root"),
        )
        return F.when(same, F.concat(F.slice(done, 1, F.size(done) - 1), F.array(longer))).otherwise(F.concat(done, F.array(new)))

    folded = per_trial.select("study", "trial", F.aggregate("p", empty, add).alias("s"))
    return folded.select("study", "trial", F.explode("s").alias("s")).select("study", "trial", "s.*").withColumn("depth", F.col("k")).select(*SEGMENT)


def nodes(segments: DataFrame) -> DataFrame:
    """One row per plan node: (path, parent, start, cfg, depth, reach, refs); reach is the last step any trial trains there."""
    return segments.groupBy("path").agg(
        F.min("parent").alias("parent"), F.min("start").alias("start"), F.min("cfg").alias("cfg"), F.min("depth").alias("depth"),
        F.max("end").alias("reach"), F.count("*").alias("refs"),
    )


def lines(segments: DataFrame) -> DataFrame:
    """(path, line): the way to each node, from its root to itself, as array<struct<path,start>>.

    One trial stands for all that pass through a node, so the ways are made once a trial and cut once a node: the
    bytes moved grow with the depth of trials, not with its square.
    """
    first = segments.groupBy("path").agg(F.min(F.struct("study", "trial", "k")).alias("r")).select("path", "r.*")
    ways = segments.groupBy("study", "trial").agg(F.array_sort(F.collect_list(F.struct("k", "path", "start"))).alias("way"))
    whole = first.join(ways, ["study", "trial"])
    line = F.transform(F.slice("way", F.lit(1), F.col("k") + 1), lambda x: F.struct(x["path"].alias("path"), x["start"].alias("start")))
    return whole.select("path", line.alias("line"))


def readable(segments: DataFrame) -> DataFrame:
    """segments with ``text``: start and configuration of each segment so far, for people; nothing is keyed by it."""
    ways = segments.groupBy("study", "trial").agg(F.array_sort(F.collect_list(F.struct("k", F.concat_ws(":", F.col("start").cast("string"), F.coalesce("cfg", F.lit("-"))).alias("x")))).alias("way"))
    text = F.array_join(F.transform(F.slice("way", F.lit(1), F.col("k") + 1), lambda x: x["x"]), "/")
    return segments.join(ways, ["study", "trial"]).withColumn("text", text).drop("way")


def salted(segments: DataFrame, sharing: str) -> DataFrame:
    """sharing: plan (one tree for all), study (one per study) or none (every trial alone, the unmerged baseline)."""
    if sharing == "plan":
        return segments
    salt = {"study": F.concat(F.lit("s"), F.col("study"), F.lit("~")), "none": F.concat(F.lit("t"), F.col("study"), F.lit("~"), F.col("trial"), F.lit("~"))}[sharing]
    return segments.withColumns({c: F.concat(salt, c) for c in ("path", "parent", "root")})


def prefix_steps(segments: DataFrame) -> DataFrame:
    """Steps of a trial before each of its segments."""
    return segments.select("study", "trial", "k", F.col("start").alias("before"), (F.col("end") - F.col("start")).alias("steps"))


def expand_steps(segments: DataFrame) -> DataFrame:
    """One row per trial and step; for small inputs and tests only, as all else works on intervals."""
    return segments.select("study", "trial", F.explode(F.sequence("start", F.col("end") - 1)).alias("step"), "cfg", "path")


def expand_udtf():
    """A table function (start, end) -> step, to be registered for SQL; one call holds one step at a time."""

    @F.udtf(returnType="step bigint")
    class ExpandRange:
        def eval(self, start: int, end: int):
            for step in range(start, end):
                yield (step,)

    return ExpandRange
