"""Exact deduplication by deterministic block naming (DataFrame functions only).

A text, lower-cased in A-Z only, is cut into blocks of a fixed number of bytes.
Distinct blocks are sorted and numbered: the number is the block's name.  Then
adjacent names are paired, distinct pairs are sorted and numbered in the same way, and
so on until a text has one name.  Two texts of as many blocks have the same last name
exactly if they are equal, as every step maps different inputs to different names.
Names follow from the set of texts alone, not from how the rows are dealt out.

Texts cross the network once, for the naming of blocks, after a partial aggregation
that merges repeated blocks.  Rows find the name of a block by a 64-bit hash; hashes that
stand for more than one block are found while naming, and their rows are matched by
content.  Nothing is decided by a hash alone.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagewise.store import Scratch

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Names are sorted numbers within so many parts of the keys, so that no task sorts all of them.
PARTS = 1 << 14


def ascii_lower(text: F.Column) -> F.Column:
    """Lower-cases A-Z only; null counts as empty."""
    text = F.coalesce(text, F.lit(""))
    plain = F.octet_length(text) == F.length(text)
    return F.when(plain, F.lower(text)).otherwise(F.translate(text, _UPPER, _UPPER.lower()))


def _blocks(content: F.Column, size: int) -> F.Column:
    """Blocks of bytes: a slice of bytes costs its own length, wherever it lies; a slice of characters all that is before it.

    The inner function gets the content as its argument, as reading a binary column copies it each time.
    """
    def cut(t: F.Column) -> F.Column:
        last = F.greatest(F.ceil(F.octet_length(t) / size).cast("int"), F.lit(1)) - 1
        return F.transform(F.sequence(F.lit(0), last), lambda i: F.substring(t, i * size + 1, F.lit(size)))

    return F.element_at(F.transform(F.array(content), cut), 1)


def _numbered(distinct: DataFrame, keys: list[str]) -> DataFrame:
    """distinct with ``name``: the part of a key, and its number in the sorted order of the part."""
    part = distinct.withColumn("part", F.pmod(F.xxhash64(*keys), F.lit(PARTS)))
    number = F.row_number().over(Window.partitionBy("part").orderBy(*keys))
    return part.withColumn("name", F.shiftleft("part", 40) + number).drop("part")


def name_texts(texts: DataFrame, scratch: Scratch, block_bytes: int = 1024, block_hash: Callable = F.xxhash64) -> DataFrame:
    """texts(doc_id, text) -> one row per input row: (row, doc_id, text_sha256, blocks int, name long).

    Rows whose (blocks, name) agree have equal normalised texts, others differ.  Order,
    repeated rows and null ids don't matter: each row is named by itself.  An empty or
    null text is one empty block.  ``block_hash`` only finds names; any function is right.
    """
    cut = texts.select("doc_id", ascii_lower(F.col("text")).cast("binary").alias("t"))
    blocks = _blocks(F.col("t"), block_bytes)
    sha = F.sha2("t", 256).alias("text_sha256")
    rows = scratch.save(
        cut.select("doc_id", sha, F.transform(blocks, lambda b: block_hash(b)).alias("h")).withColumn(
            "row", F.monotonically_increasing_id()
        ),
        "rows",
    )
    block = cut.select(F.explode(blocks).alias("block")).select(block_hash("block").alias("h"), "block")
    # where a hash stands for one block, the order of hashes is an order of blocks
    of_hash = scratch.save(_numbered(block.distinct().groupBy("h").agg(F.count("*").alias("n")), ["h"]), "of_hash")
    at = rows.select("row", F.size("h").alias("n"), F.posexplode("h").alias("k", "h"))
    level = at.join(of_hash.where("n = 1").select("h", "name"), "h").select("row", "n", "k", "name")
    if of_hash.where("n > 1").limit(1).count():
        level = level.unionByName(_by_content(cut, blocks, sha, rows, at, of_hash.where("n > 1").select("h"), block_hash, scratch))
    level = scratch.save(level, "level-0")
    done, step = [level.where("n = 1").select("row", "name")], 0
    longest = rows.agg(F.max(F.size("h"))).first()[0] or 1
    while longest > 1:
        step, longest = step + 1, (longest + 1) // 2
        # a text of one name is done: its number of blocks tells at which level, so names of levels never mix
        pairs = scratch.save(
            level.where("n > 1")
            .groupBy("row", F.expr("k div 2").alias("k"))
            .agg(
                F.max(F.expr("(n + 1) div 2").cast("int")).alias("n"),
                F.max(F.when(F.col("k") % 2 == 0, F.col("name"))).alias("left"),
                F.max(F.when(F.col("k") % 2 == 1, F.col("name"))).alias("right"),
            ),
            f"pairs-{step}",
        )
        named = scratch.save(_numbered(pairs.select("left", "right").distinct(), ["left", "right"]), f"names-{step}")
        level = scratch.save(
            pairs.alias("p").join(named.alias("q"), F.expr("p.left = q.left and p.right <=> q.right")).select("row", "n", "k", "name"),
            f"level-{step}",
        )
        scratch.drop(f"pairs-{step}", f"names-{step}")
        done.append(level.where("n = 1").select("row", "name"))
    last = reduce(DataFrame.unionByName, done)
    return rows.select("row", "doc_id", "text_sha256", F.size("h").alias("blocks")).join(last, "row")


def _by_content(cut, blocks, sha, rows, at, unsure, block_hash, scratch) -> DataFrame:
    """Names of the blocks whose hash stands for several blocks: below all other names, found by their content."""
    full = cut.select("doc_id", sha, F.posexplode(blocks).alias("k", "block")).withColumn("h", block_hash("block"))
    full = full.join(unsure, "h", "left_semi")
    named = scratch.save(_numbered(full.select("h", "block").distinct(), ["h", "block"]), "unsure")
    known = full.join(named, ["h", "block"]).select("doc_id", "text_sha256", "k", (-1 - F.col("name")).alias("name")).distinct()
    doubt = at.join(unsure, "h", "left_semi").join(rows.select("row", "doc_id", "text_sha256"), "row")
    same = F.expr("d.doc_id <=> n.doc_id and d.text_sha256 = n.text_sha256 and d.k = n.k")
    return doubt.alias("d").join(known.alias("n"), same).select("d.row", "d.n", "d.k", "n.name")


def exact_duplicates(docs: DataFrame, block_bytes: int = 1024) -> DataFrame:
    """docs(doc_id, text, ...) -> (doc_id, keep_id, group_size, kept, text_sha256), one row per input row.

    Texts are equal when identical after lower-casing A-Z; null is empty.  The row with the
    largest doc_id stays; of rows that tie on it exactly one stays.  A null doc_id is below
    all others.  Columns other than doc_id and text are not read.
    """
    scratch = Scratch(docs.sparkSession, "exact")
    named = scratch.save(name_texts(docs.select("doc_id", "text"), scratch, block_bytes), "named")
    groups = scratch.save(
        named.groupBy("blocks", "name").agg(F.max(F.struct("doc_id", "row")).alias("best"), F.count("*").alias("group_size")), "groups"
    )
    return named.join(groups, ["blocks", "name"]).select(
        "doc_id",
        F.col("best.doc_id").alias("keep_id"),
        "group_size",
        (F.col("row") == F.col("best.row")).alias("kept"),
        "text_sha256",
    )


def keep_one(docs: DataFrame, block_bytes: int = 1024) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns.

    Rows that agree in doc_id and text are interchangeable; one of them stays.
    """
    found = exact_duplicates(docs, block_bytes)
    winners = found.where("kept").select(F.col("doc_id").alias("__id"), F.col("text_sha256").alias("__sha"))
    keyed = docs.withColumn("__key", F.sha2(ascii_lower(docs["text"]).cast("binary"), 256))
    stay = keyed.join(winners, keyed["doc_id"].eqNullSafe(F.col("__id")) & (F.col("__key") == F.col("__sha")), "left_semi")
    return stay.dropDuplicates(["doc_id", "__key"]).drop("__key")
