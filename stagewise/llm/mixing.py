"""Temperature mixing of sources, realised as budgeted block permutations.

Token shares of sources are raised to an exponent and normalised; a bisection finds the
exponent that meets a target entropy or the largest one that keeps repetition within a limit.
The smallest budget that shows every document of the largest source at least once is
then spent.  Each source has a keyed permutation of its documents, the order of a 60-bit rank of
source, id and text; it is passed over as often as its weight asks, the last time up to the rank
where its budget is used up.  A showing lies in its source's stream at (pass + rank as a fraction) of
all passes, and these places, alike for all sources, are cut into blocks of a token budget: every
block holds the sources at their target weights, in a permuted order.

The rank and a row per source decide everything, so texts are read, not joined.  Tokens are summed
over ranges of ranks first, so no source is ordered in one task.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stagewise.store import Scratch

#: Sources up to which their budgets are broadcast (some 50 bytes each); more of them meet the rows by a shuffle.
FEW_SOURCES = 100_000
RANK_BITS = 60
TASK_TOKENS = 1 << 24  # of the blocks that one task writes: some 120 MB of text
RANGE_ROWS = 4096  # rows of a range of ranks, whose order one task decides


def weights(shares: list[float], exponent: float) -> list[float]:
    top = max(shares)
    raw = [(x / top) ** exponent if x > 0 else 0.0 for x in shares]
    total = sum(raw)
    return [x / total for x in raw]


def entropy(p: list[float]) -> float:
    return -sum(x * math.log(x) for x in p if x > 0)


def repetitions(shares: list[float], exponent: float) -> list[float]:
    """Passes over each source when the least repeated one is passed over once."""
    w = weights(shares, exponent)
    ratio = [a / b if b > 0 else 0.0 for a, b in zip(w, shares)]
    least = min(x for x in ratio if x > 0)
    return [x / least for x in ratio]


def _least(fails, steps: int = 60) -> float:
    """The least exponent in [0, 1] that does not fail, by bisection."""
    if not fails(0.0):
        return 0.0
    low, high = 0.0, 1.0
    for _ in range(steps):
        mid = (low + high) / 2
        low, high = (mid, high) if fails(mid) else (low, mid)
    return high


def solve_exponent(shares: list[float], target_entropy: float | None = None, most_repeated: float | None = None, steps: int = 60) -> float:
    """The exponent in [0, 1] by bisection: 1 keeps the shares, 0 makes all sources equal.

    Entropy and repetition both fall as the exponent grows.  A target entropy outside the
    reachable range gives the nearest end.  With both given, the larger exponent holds.
    """
    found = 0.0 if target_entropy is not None or most_repeated is not None else 1.0
    if target_entropy is not None:
        found = max(found, _least(lambda x: entropy(weights(shares, x)) > target_entropy, steps))
    if most_repeated is not None:
        found = max(found, _least(lambda x: max(repetitions(shares, x)) > most_repeated, steps))
    return found


def solve_totals(totals: DataFrame, target_entropy: float | None = None, most_repeated: float | None = None) -> float:
    """:func:`solve_exponent` of the shares in totals(total), any number of them: only sums reach the driver."""
    ends = totals.agg(F.min("total").alias("low"), F.max("total").alias("top"), F.sum("total").alias("all")).first()
    # the most and the least repeated sources are the smallest and the largest
    found = solve_exponent([ends.low / ends.all, ends.top / ends.all], None, most_repeated)
    if target_entropy is None:
        return found
    like = totals.groupBy("total").agg(F.count("*").alias("n")).persist()

    def spread(x: float) -> float:
        raw = F.pow(F.col("total") / ends.top, F.lit(x))
        r = like.agg(F.sum(F.col("n") * raw).alias("z"), F.sum(F.col("n") * raw * F.log(raw)).alias("h")).first()
        return math.log(r.z) - r.h / r.z

    wanted = _least(lambda x: spread(x) > target_entropy)
    like.unpersist()
    return wanted if most_repeated is None else max(found, wanted)


def token_count(text: Column) -> Column:
    """Words of a text by single spaces and line feeds, at least 1: the unit of budgets."""
    text = F.coalesce(text, F.lit(""))
    plain = F.translate(text, "\n", " ")
    return (F.length(plain) - F.length(F.replace(plain, F.lit(" "), F.lit(""))) + 1).cast("long")


def rank_of(doc_id: Column, source: Column, text: Column, seed: int) -> Column:
    """The place of a row in its source's permutation: 60 bits, in an order that any engine repeats (md5)."""
    key = F.concat_ws("|", F.lit(str(seed)), F.coalesce(source.cast("string"), F.lit("")), F.coalesce(doc_id.cast("string"), F.lit("")), F.md5(F.coalesce(text, F.lit("")).cast("binary")))
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, RANK_BITS // 4), 16, 10).cast("long")


def _budgets(rows: DataFrame, scratch: Scratch, target_entropy: float | None, most_repeated: float | None) -> tuple[DataFrame, int]:
    """rows(source, tokens, rank) -> (s, passes, whole, cut) a source and the tokens of all showings.

    A row is shown ``whole`` times, and once more if its rank is at most ``cut``; ``passes`` is what the budget holds.
    """
    n = rows.count()
    bits = max(0, min(20, math.ceil(math.log2(max(1, n / RANGE_ROWS)))))
    part = F.shiftright("rank", RANK_BITS - bits).alias("part")
    sums = scratch.save(rows.groupBy("source", part).agg(F.sum("tokens").alias("tokens")), "sums")
    totals = scratch.save(sums.groupBy("source").agg(F.sum("tokens").alias("total")), "totals")
    top = totals.agg(F.max("total")).first()[0]
    # the largest source is passed over once, the others as the exponent asks
    exponent = solve_totals(totals, target_entropy, most_repeated) if top else 1.0
    passes = F.pow(F.lit(float(top or 1)) / F.col("total"), F.lit(1 - exponent))
    budget = totals.select(F.col("source").alias("s"), "total", F.floor(passes + 1e-9).cast("long").alias("whole"), passes.alias("passes"))
    budget = budget.withColumn("room", F.greatest(F.floor((F.col("passes") - F.col("whole")) * F.col("total") + 1e-6), F.lit(0)).cast("long"))
    upto = F.sum("tokens").over(Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, 0))
    ranges = sums.withColumn("upto", upto).join(budget, F.col("source").eqNullSafe(F.col("s")))
    # the range in which the budget of the last pass ends, the first that does not fit as a whole
    ends = ranges.where("upto > room").groupBy("s").agg(F.min(F.struct("part", (F.col("upto") - F.col("tokens")).alias("before"), "room")).alias("e"))
    ends = scratch.save(ends.select("s", "e.*").where("room > 0"), "ends")
    inside = rows.withColumn("at", part).join(_small(ends.select(F.col("s").alias("es"), "part", "before", "room")), F.col("source").eqNullSafe(F.col("es")) & (F.col("at") == F.col("part")))
    upto = F.col("before") + F.sum("tokens").over(Window.partitionBy("es", "part").orderBy("rank").rangeBetween(Window.unboundedPreceding, 0))
    last = inside.withColumn("upto", upto).where("upto <= room").groupBy("es").agg(F.max("rank").alias("rank"))
    cut = ends.join(last, F.col("s").eqNullSafe(F.col("es")), "left").select("s", F.coalesce("rank", F.shiftleft("part", RANK_BITS - bits) - 1).alias("cut"))
    out = budget.alias("b").join(cut.withColumnRenamed("s", "cs"), F.expr("b.s <=> cs"), "left").select(
        "s", "whole", (F.col("whole") + F.col("room") / F.col("total")).alias("passes"), F.coalesce("cut", F.lit(-1).cast("long")).alias("cut"), F.col("whole") * F.col("total") + F.col("room")
    ).toDF("s", "whole", "passes", "cut", "shown")
    out = scratch.save(out, "budgets")
    return out.drop("shown"), out.agg(F.sum("shown")).first()[0] or 0


def _small(table: DataFrame) -> DataFrame:
    """Broadcast if it has few rows, which is counted."""
    return F.broadcast(table) if table.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES else table


def _shown(rows: DataFrame, source: Column, rank: Column, budgets: DataFrame, shown: int, block_tokens: int) -> DataFrame:
    """rows, each as often as it is shown, with __pass, __passes, __place (in 0 to 1) and __block."""
    b = budgets.select(*[F.col(c).alias(f"__{c}") for c in ("s", "whole", "passes", "cut")])
    if budgets.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES:
        known = rows.join(F.broadcast(b), source.eqNullSafe(F.col("__s")))
    else:  # a source of very many rows is dealt over 16 tasks at least
        wide = b.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(15))))
        known = rows.join(wide, source.eqNullSafe(F.col("__s")) & (F.pmod(rank, F.lit(16)) == F.col("__salt")))
    times = F.col("__whole") + (rank <= F.col("__cut")).cast("long")
    known = known.withColumn("__times", times).withColumn("__pass", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__times") - 1)))
    place = (F.col("__pass") + rank / float(1 << RANK_BITS)) / F.col("__passes")
    blocks = max(1, -(-shown // block_tokens))
    # the last budget may end a little after its hashed fraction
    return known.withColumn("__place", place).withColumn("__block", F.least(F.floor(F.col("__place") * blocks), F.lit(blocks - 1)).cast("long"))


def plan_mix(
    docs: DataFrame, target_entropy: float | None = None, most_repeated: float | None = 1.5, block_tokens: int = 1 << 18, seed: int = 1
) -> DataFrame:
    """docs(doc_id, text, source, ...) -> (doc_id, source, tokens, rank, pass, passes, block, position), one row per showing.

    ``pass`` counts a row's showings from 0 and ``passes`` is their number: the whole passes over its source, and one more
    where the permuted order of its source comes to it before the source's budget ends.  Showings are read block by block, in
    the order of ``position`` within a block.
    A null source is a source of its own, and null ids and texts count as empty.  Rows alike in doc_id, text and source
    have one place in the order.  No row is dropped: the least repeated source is shown once.  No rows give no rows.
    """
    scratch = Scratch(docs.sparkSession, "mix")
    rows = docs.select("doc_id", "source", token_count(F.col("text")).alias("tokens"), rank_of(F.col("doc_id"), F.col("source"), F.col("text"), seed).alias("rank"))
    rows = scratch.save(rows, "rows")
    budgets, shown = _budgets(rows, scratch, target_entropy, most_repeated)
    out = _shown(rows, F.col("source"), F.col("rank"), budgets, shown, block_tokens)
    position = F.row_number().over(Window.partitionBy("__block").orderBy("__place", "rank", F.coalesce(F.col("source").cast("string"), F.lit("")))) - 1
    return out.select(
        "doc_id", "source", "tokens", "rank", F.col("__pass").alias("pass"), F.col("__times").alias("passes"), F.col("__block").alias("block"), position.cast("long").alias("position")
    )


def mix(docs: DataFrame, target_entropy: float | None = None, most_repeated: float | None = 1.5, block_tokens: int = 1 << 18, seed: int = 1) -> DataFrame:
    """The rows of ``docs``, all columns, each as often as :func:`plan_mix` shows it, block by block.

    A task holds whole blocks, in order.  Budgets come from narrow rows; texts are moved once, to their blocks.
    """
    scratch = Scratch(docs.sparkSession, "mixed")
    rank = rank_of(docs["doc_id"], docs["source"], docs["text"], seed)
    rows = scratch.save(docs.select(docs["source"], token_count(docs["text"]).alias("tokens"), rank.alias("rank")), "rows")
    budgets, shown = _budgets(rows, scratch, target_entropy, most_repeated)
    ranked = docs.withColumn("__rank", rank)
    out = _shown(ranked, ranked["source"], F.col("__rank"), budgets, shown, block_tokens)
    # neighbouring blocks share a task, as many as make up TASK_TOKENS; few blocks are dealt over all tasks there are
    blocks = max(1, -(-shown // block_tokens))
    tasks = min(blocks, max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-shown // TASK_TOKENS)))
    dealt = out.repartitionById(tasks, F.floor(F.col("__block") * tasks / blocks).cast("int"))
    return dealt.sortWithinPartitions("__block", "__place").select(*[docs[c] for c in docs.columns])
