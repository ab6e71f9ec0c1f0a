"""Near-duplicate documents by fast similarity sketching, banding and exact verification.

A document is the set of its distinct word shingles, each a 64-bit mix of its words' BLAKE2 digests.  Its sketch comes from rounds of
hashed bin placement (:func:`stagewise.llm.texthash.similarity_sketch`); bands of
coordinates that agree make two sets candidates, and 100 * intersection >= 80 * union on the
full sets makes them linked.  With 51 bands of 5 coordinates a pair at similarity 0.8 is
missed with a probability below 1e-8.

Equal sets are merged before anything is compared, so copies cost one row.  Within a
bucket, members are first compared with one member; a bucket whose members are then in
one component is done.  In buckets that still hold several components, the rows outside the
main one are queries against all rows of the bucket, in chunks that give only links.  So no link
between components is lost, and a bucket of n near copies never makes n * n rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.llm import texthash
from stagewise.llm.components import connected_components
from stagewise.store import Scratch

BANDS, ROWS = 51, 5
_SKETCH = "doc_id long, text_key long, n long, d1 long, d2 long, bands array<long>"
_SETS = "gid long, shingles array<long>"


def _signatures(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        np.seterr(over="ignore")
        for batch in batches:
            for part in texthash.slices(batch, "text"):
                flat, sizes = texthash.shingle_sets(*texthash.text_bytes(part.column("text")), width)
                keys = texthash.band_keys(texthash.similarity_sketch(flat, sizes, BANDS * ROWS), ROWS)
                d1, d2 = texthash.set_digests(flat, sizes)
                at = np.concatenate([[0], np.cumsum(np.where(sizes > 0, BANDS, 0))]).astype(np.int32)
                bands = pa.ListArray.from_arrays(pa.array(at), pa.array(keys[sizes > 0].reshape(-1)))
                cols = [part.column("doc_id"), part.column("text_key"), pa.array(sizes), pa.array(d1), pa.array(d2), bands]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "text_key", "n", "d1", "d2", "bands"])
                texthash.trim()
        texthash.give_back()

    return run


def _full_sets(width: int):
    """Rows (gid, d1, d2, text) -> the set of each text that has these digests."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        np.seterr(over="ignore")
        for batch in batches:
            for part in texthash.slices(batch, "text"):
                flat, sizes = texthash.shingle_sets(*texthash.text_bytes(part.column("text")), width)
                d1, d2 = texthash.set_digests(flat, sizes)
                own = (d1 == part.column("d1").to_numpy()) & (d2 == part.column("d2").to_numpy())
                at = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
                sets = pa.ListArray.from_arrays(pa.array(at), pa.array(flat.view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column("gid"), sets], names=["gid", "shingles"]).filter(pa.array(own))
                texthash.trim()
        texthash.give_back()

    return run


def _dealt(rows: DataFrame, table: DataFrame, key: str, how: str = "inner", salts: int = 8) -> DataFrame:
    """rows(key, gid, ..) joined with table(key, ..), which has one row a key; the rows of one key are dealt over ``salts`` tasks."""
    wide = table.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return rows.withColumn("salt", F.pmod(F.xxhash64("gid"), F.lit(salts)).cast("int")).join(wide, [key, "salt"], how).drop("salt")


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """pairs(a, b) -> those whose full sets have a Jaccard similarity of percent / 100 or more."""
    left = pairs.join(sets.select(F.col("gid").alias("b"), F.col("shingles").alias("y")), "b")
    both = left.join(sets.select(F.col("gid").alias("a"), F.col("shingles").alias("x")), "a")
    common = F.size(F.array_intersect("x", "y")).cast("long")
    union = F.size("x") + F.size("y") - common
    # sizes alone rule out many pairs before any set is read
    able = 100 * F.least(F.size("x"), F.size("y")) >= percent * F.greatest(F.size("x"), F.size("y"))
    return both.where(able).where(100 * common >= percent * union).select("a", "b")


def _blocks_linked(percent: int):
    """One base component, one chunk of its rows: links of the queries to rows of other components, as pairs of roots."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        queries, targets = group[group["query"]], group[~group["query"]]
        edges: set[tuple[int, int]] = set()
        if len(queries) and len(targets):
            sizes = np.array([len(x) for x in targets["shingles"]])
            flat = np.concatenate(list(targets["shingles"]))
            order = np.argsort(flat, kind="stable")
            owner = np.repeat(np.arange(len(targets)), sizes)[order]
            known, first, count = np.unique(flat[order], return_index=True, return_counts=True)
            roots = targets["root"].to_numpy()
            for root, own in zip(queries["root"], queries["shingles"]):
                at = np.minimum(np.searchsorted(known, own), len(known) - 1)
                at = at[known[at] == own]
                n = count[at]
                where = np.repeat(first[at] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
                common = np.bincount(owner[where], minlength=len(targets))
                linked = 100 * common >= percent * (len(own) + sizes - common)
                edges |= {(root, r) for r in np.unique(roots[linked]).tolist() if r != root}
        rows = sorted(edges)
        return pd.DataFrame({"a": [x for x, _ in rows], "b": [y for _, y in rows]}).astype("int64")

    return run


def _between(placed: DataFrame, sets: DataFrame, percent: int, only_first: bool, chunk: int = 256) -> DataFrame:
    """placed(key, gid, root): links between components that share a bucket, as pairs of roots.

    In each bucket of several components the rows outside of its main one are queries against all its rows.
    Queries and rows are gathered per main component, over all its buckets, and compared in chunks
    of rows; ``only_first`` takes one chunk of each, which settles most queries cheaply.
    """
    parts = placed.groupBy("key", "root").agg(F.count("*").alias("n"))
    mixed = parts.groupBy("key").agg(F.max(F.struct("n", "root")).alias("main"), F.count("*").alias("roots")).where("roots > 1")
    rows = _dealt(placed, mixed.select("key", F.col("main.root").alias("base")), "key").select("base", "gid", "root").distinct()
    asked = F.count(F.when(F.col("root") != F.col("base"), 1))
    sizes = rows.groupBy("base").agg(
        F.ceil(F.count("*") / chunk).cast("int").alias("chunks"), F.ceil(asked / (2 * chunk)).cast("int").alias("parts")
    )
    rows = rows.join(sizes, "base").join(sets, "gid")
    place = F.xxhash64("gid")
    targets = rows.withColumns({"query": F.lit(False), "chunk": F.pmod(place, F.col("chunks")).cast("int")})
    targets = (targets.where("chunk = 0") if only_first else targets).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    chunks = F.array(F.lit(0)) if only_first else F.sequence(F.lit(0), F.col("chunks") - 1)
    part = F.pmod(F.xxhash64(place), F.col("parts")).cast("int")
    queries = rows.where("root <> base").withColumns({"query": F.lit(True), "part": part}).withColumn("chunk", F.explode(chunks))
    both = queries.unionByName(targets).select("base", "chunk", "part", "query", "root", "shingles")
    return both.groupBy("base", "chunk", "part").applyInPandas(_blocks_linked(percent), "a long, b long")


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """docs(doc_id long, text, ...) -> (doc_id, text_key, n_shingles, component_id, group_key, kept), one row per input row.

    ``n_shingles`` is the size of the row's set of ``width``-word shingles; a text with
    fewer words has one, a null or wordless text none and is linked with nothing.  Links
    are pairs of rows with similarity >= ``percent`` / 100; ``component_id`` is the smallest
    doc_id reachable over links, itself included; ``kept`` holds where it is the row's own.
    Rows without doc_id are linked with nothing and have no component_id.  ``text_key`` is a
    hash of the text, which tells rows of one doc_id apart.  Other columns are not read, whatever their names.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "near")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("text_key", F.xxhash64("text"))
    rows = scratch.save(texts.mapInArrow(_signatures(width), _SKETCH), "rows")
    able = rows.where("n > 0 and doc_id is not null")
    groups = scratch.save(
        able.groupBy("n", "d1", "d2")
        .agg(F.min("doc_id").alias("doc"), F.any_value("bands").alias("bands"))
        .withColumn("gid", F.monotonically_increasing_id()),
        "groups",
    )
    banded = groups.select(F.explode("bands").alias("key"), "gid")
    buckets = scratch.save(
        banded.groupBy("key").agg(F.min("gid").alias("lo"), F.max("gid").alias("hi"), F.count("*").alias("c")).where("lo < hi"), "buckets"
    )
    members = scratch.save(_dealt(banded, buckets.where("c > 2").select("key", "lo"), "key").select("key", "gid", "lo"), "members")
    pairs = buckets.where("c = 2").select(F.col("lo").alias("a"), F.col("hi").alias("b")).unionByName(
        members.where("gid <> lo").select(F.col("lo").alias("a"), F.col("gid").alias("b"))
    )
    pairs = scratch.save(pairs.distinct(), "pairs")
    asked = pairs.select(F.explode(F.array("a", "b")).alias("gid")).distinct()
    wanted = groups.select("gid", "doc", "d1", "d2").join(asked, "gid", "left_semi")
    found = texts.join(wanted, texts["doc_id"] == wanted["doc"]).select("gid", "d1", "d2", "text")
    sets = scratch.save(found.mapInArrow(_full_sets(width), _SETS).dropDuplicates(["gid"]), "sets")
    roots = connected_components(_verified(pairs, sets, percent), scratch)
    root = F.coalesce("root", "gid").alias("root")
    placed = scratch.save(members.join(roots, F.col("gid") == F.col("id"), "left").select("key", "gid", root), "placed-0")
    named = scratch.save(groups.select("gid", "n", "d1", "d2", "doc").join(roots, F.col("gid") == F.col("id"), "left").select("gid", "n", "d1", "d2", "doc", root), "named-0")
    scratch.drop("buckets", "members", "pairs", "groups")
    for k, only_first in ((1, True), (2, False)):
        joined = connected_components(_between(placed, sets, percent, only_first), scratch, f"cc-{k}").select(F.col("id").alias("root"), F.col("root").alias("to"))
        new = F.coalesce("to", "root").alias("root")
        named = scratch.save(_dealt(named, joined, "root", "left").select("gid", "n", "d1", "d2", "doc", new), f"named-{k}")
        if only_first:
            placed = scratch.save(_dealt(placed, joined, "root", "left").select("key", "gid", new), f"placed-{k}")
        scratch.drop(f"placed-{k - 1}", f"named-{k - 1}")
    smallest = named.groupBy("root").agg(F.min("doc").alias("component_id"))
    of_set = scratch.save(_dealt(named, smallest, "root").select("n", "d1", "d2", "component_id", F.col("root").alias("group_key")), "of_set")
    scratch.drop("sets")
    out = rows.select("doc_id", "text_key", "n", "d1", "d2").join(of_set, ["n", "d1", "d2"], "left")
    own = F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "text_key", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), own).alias("component_id"), "group_key")
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)))


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """One row of each group of near-duplicates, with all columns of ``docs``: that of the smallest doc_id.

    Rows without doc_id stay; of rows that repeat a doc_id within a group the one with the least text hash stays.
    """
    found = near_duplicates(docs, width, percent)
    best = found.where("kept").groupBy(F.col("doc_id").alias("__id"), "group_key").agg(F.min("text_key").alias("__stays"))
    keyed = docs.withColumn("__key", F.xxhash64(docs["text"]))
    named = keyed.where(docs["doc_id"].isNotNull())
    stay = named.join(best, (named["doc_id"].cast("long") == F.col("__id")) & (F.col("__key") == F.col("__stays")), "left_semi")
    return stay.dropDuplicates(["doc_id", "__key"]).unionByName(keyed.where(docs["doc_id"].isNull())).drop("__key")
