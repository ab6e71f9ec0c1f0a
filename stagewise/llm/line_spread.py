"""Cross-site boilerplate lines by the number of distinct sites that show them.

Sites per line are counted by HyperLogLog sketches that merge in aggregation.  A line
whose estimate is near the threshold gets an exact distinct count.  Lines shown by enough
sites are removed, from all documents but the first that has them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.store import Scratch


def _lines(text: F.Column) -> F.Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _keyed(docs: DataFrame) -> DataFrame:
    lines = docs.select("doc_id", F.xxhash64("text").alias("text_key"), F.xxhash64("source").alias("site"), F.posexplode(_lines(F.col("text"))).alias("pos", "line"))
    # blank lines hold nothing to repeat
    line = lines.withColumn("line", F.trim("line")).where("line <> ''")
    return line.select("doc_id", "text_key", "site", "pos", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2"))


def spread_lines(docs: DataFrame, scratch: Scratch, min_sites: int = 10, lg_k: int = 10) -> DataFrame:
    """(h1, h2) of the lines that at least ``min_sites`` distinct sources show; a null source is one site."""
    lines = _keyed(docs)
    several = lines.groupBy("h1", "h2").agg(F.min("site").alias("a"), F.max("site").alias("b"), F.count("*").alias("n"), F.min("doc_id").alias("first"))
    # a line of fewer occurrences than the threshold, or of one site, cannot reach it
    several = scratch.save(several.where(f"n >= {min_sites} and (a < b or {min_sites} <= 1)").select("h1", "h2", "first"), "several")
    seen = lines.join(several, ["h1", "h2"])
    sketches = seen.groupBy("h1", "h2", "first").agg(F.hll_sketch_estimate(F.hll_sketch_agg("site", lg_k)).alias("sites"))
    sketches = scratch.save(sketches, "sketches")
    error = 4 * 1.04 / 2 ** (lg_k / 2)
    low, high = min_sites * (1 - error) - 1, min_sites * (1 + error) + 1
    near = sketches.where(F.col("sites").between(low, high)).select("h1", "h2", "first")
    pairs = lines.join(near, ["h1", "h2"]).groupBy("h1", "h2", "first", "site").agg(F.lit(1).alias("one"))
    exact = pairs.groupBy("h1", "h2", "first").agg(F.count("*").alias("sites")).where(F.col("sites") >= min_sites)
    return exact.select("h1", "h2", "first").unionByName(sketches.where(F.col("sites") > high).select("h1", "h2", "first"))


def remove_boilerplate(docs: DataFrame, min_sites: int = 10, lg_k: int = 10) -> DataFrame:
    """docs(doc_id, text, source, ...) -> (doc_id, text, n_lines, n_removed), one row per input row.

    Lines are separated by a line feed and compared after trimming spaces; blank lines stay.
    A line shown by at least ``min_sites`` sources goes from every document but that of
    its smallest doc_id.  Null texts give an empty text.  Rows alike in doc_id and text are treated alike.
    """
    scratch = Scratch(docs.sparkSession, "lines")
    docs = docs.select("doc_id", "text", "source")
    bad = scratch.save(spread_lines(docs, scratch, min_sites, lg_k), "bad")
    hits = _keyed(docs).join(bad, ["h1", "h2"]).where("not (doc_id <=> first)")
    gone = hits.groupBy(F.col("doc_id").alias("id"), "text_key").agg(F.collect_set("pos").alias("gone"))
    keyed = docs.withColumn("key", F.xxhash64("text"))
    out = keyed.join(gone, keyed["doc_id"].eqNullSafe(F.col("id")) & (F.col("key") == F.col("text_key")), "left")
    # a column of its own, so that a text is split once
    out, lines = out.withColumn("lines", _lines(F.col("text"))), F.col("lines")
    # the positions that stay come from one hashed difference, so a document takes time in proportion to its lines
    stay = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), "gone")
    rest = F.transform(stay, lambda i: F.element_at(lines, i + 1))
    text = F.when(F.col("gone").isNull(), F.coalesce("text", F.lit(""))).otherwise(F.array_join(rest, "\n"))
    return out.select("doc_id", text.alias("text"), F.size(lines).cast("long").alias("n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"))
