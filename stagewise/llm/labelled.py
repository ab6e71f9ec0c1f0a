"""Bounded samples of labelled documents, for fitting classifiers."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


#: Parts of a sample, each of which one task learns from.
SHARDS = 8


def held_out(doc_id: F.Column) -> F.Column:
    """Rows whose label no classifier learns: crc32 of the id as text, modulo 4, is 2."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def fit_sample(docs: DataFrame, labels: DataFrame, label: str, rows: int, extra: tuple[str, ...] = (), most_of_one: float = 1.0) -> DataFrame:
    """At most ``rows`` labelled rows that are not held out, those of the least id hashes: (doc_id, label, shard, text, extra columns).

    Ids without a document, null labels and null texts are left out; a repeated id counts once, with the least of its texts.
    Texts are whole; only their number is bounded.  ``shard`` is one of SHARDS, by the id's hash.
    ``most_of_one`` below 1 takes that share of ``rows`` of each label at most, for rare labels.
    """
    known = labels.select("doc_id", F.col(label).alias("label")).where(F.col("label").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("label").cast("int").alias("label"))
    if most_of_one < 1:
        each = int(rows * most_of_one)
        first = known.where("label = 1").orderBy(F.xxhash64("doc_id"), "doc_id").limit(each)
        second = known.where("label = 0").orderBy(F.xxhash64("doc_id"), "doc_id").limit(each)
        known = first.unionByName(second)
    else:
        known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    # columns are picked before the join, so that those of docs cannot clash; at most ``rows`` ids are broadcast
    own = docs.select("doc_id", "text", *extra).where(F.col("text").isNotNull()).join(F.broadcast(known), "doc_id")
    own = own.groupBy("doc_id", "label").agg(F.min(F.struct("text", *extra)).alias("x")).select("doc_id", "label", "x.*")
    return own.withColumn("shard", F.pmod(F.xxhash64(F.lit(SHARDS), "doc_id"), F.lit(SHARDS)).cast("int"))


def auc(score, label) -> float:
    order = pd.Series(score).rank()
    pos = label == 1
    n, m = int(pos.sum()), int((~pos).sum())
    return float((order[pos].sum() - n * (n + 1) / 2) / (n * m)) if n and m else float("nan")
