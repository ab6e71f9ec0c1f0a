"""Connected components of a link table, without gathering links anywhere.

Each round points every vertex at the smallest vertex of its neighbourhood, once
over the larger and once over the smaller neighbours; a component ends as a star
around its smallest vertex after a number of rounds logarithmic in its size.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.store import Scratch


def connected_components(edges: DataFrame, scratch: Scratch, tag: str = "cc") -> DataFrame:
    """edges(a long, b long) -> (id, root): the smallest id of the component of each linked id.

    Null ends and loops are ignored; repeated links are harmless; no links give no rows.
    """
    now = scratch.save(
        edges.where("a <> b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("m")).distinct(), f"{tag}-0"
    )
    k = 0
    while not _stars(now):
        k += 1
        both = now.select(F.col("v").alias("u"), F.col("m").alias("w")).unionByName(now.select(F.col("m").alias("u"), F.col("v").alias("w")))
        # written first, so that both inputs of the join are plain exchanges and a vertex of very many links is split
        least = scratch.save(both.groupBy("u").agg(F.least(F.min("w"), F.first("u")).alias("m")), f"{tag}-{k}-least")
        large = scratch.save(both.where("w > u").join(least, "u").select(F.col("w").alias("v"), "m").where("v <> m").distinct(), f"{tag}-{k}-large")
        low = large.groupBy("v").agg(F.min("m").alias("low"))
        small = large.join(low, "v").select(F.explode(F.array("v", "m")).alias("v"), F.col("low").alias("m"))
        now = scratch.save(small.where("v <> m").distinct(), f"{tag}-{k}")
        scratch.drop(f"{tag}-{k}-least", f"{tag}-{k}-large", f"{tag}-{k - 1}")
    roots = now.select(F.col("v").alias("id"), F.col("m").alias("root"))
    return roots.unionByName(now.select(F.col("m").alias("id"), F.col("m").alias("root")).distinct())


def _stars(now: DataFrame) -> bool:
    """Whether every vertex points at one vertex that points nowhere."""
    told = now.select(F.col("v").alias("x"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(
        now.select(F.col("m").alias("x"), F.lit(0).alias("out"), F.lit(1).alias("into"))
    )
    wrong = told.groupBy("x").agg(F.sum("out").alias("out"), F.max("into").alias("into")).where("out > 1 or (out > 0 and into > 0)")
    return not wrong.limit(1).count()
