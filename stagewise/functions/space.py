"""Search spaces: grids of setting functions, conditional filters, seeded samples."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagewise.functions import hpfunc as H

SCHEMA = "study string, trial bigint, ord bigint, cfg string, steps bigint"


def grid(spark: SparkSession, study: str, space: dict[str, list], where: Callable[[dict], bool] | None = None) -> DataFrame:
    """Pieces of every combination; a space is a client's list, so the product is made where the client is."""
    rows, trial = [], 0
    for combo in product(*[space[k] for k in space]):
        own = dict(zip(space, combo))
        if where is not None and not where(own):
            continue
        for k, (start, end, cfg) in enumerate(H.align(own)):
            rows.append((study, trial, k, cfg, end - start))
        trial += 1
    return spark.createDataFrame(rows, SCHEMA)


def of_parts(parts: DataFrame, n: int = 120) -> DataFrame:
    """Pieces of grids that a catalogue of parts names, one study for each type (its name in hexadecimal digits), every combination a trial of n steps.

    A type's sizes are first milestones of a learning rate that decays there and 60 steps later, its brands' numbers those of a
    batch size that doubles at 20 and four steps a number.  Milestones at or beyond the end vanish.
    """
    typed = parts.where("p_type is not null").withColumn("study", F.hex("p_type"))
    lr = typed.where("p_size is not null").select("study", F.col("p_size").cast("long").alias("m")).distinct()
    bs = typed.select("study", F.regexp_extract("p_brand", "([0-9]+)$", 1).try_cast("long").alias("b")).where("b is not null").distinct()
    first, second, double = F.col("m"), F.col("m") + 60, 20 + 4 * F.col("b")
    inside = [F.least(F.greatest(x, F.lit(0).cast("long")), F.lit(n).cast("long")) for x in (first, second, double)]
    cuts = F.array_sort(F.array_distinct(F.array(F.lit(0).cast("long"), *inside, F.lit(n).cast("long"))))
    spans = lr.join(bs, "study").withColumn("cuts", cuts).select("*", F.posexplode(F.slice("cuts", F.lit(1), F.size("cuts") - 1)).alias("ord", "lo"))
    cfg = F.concat(
        F.lit("bs=constant("), F.when(F.col("lo") < double, "128").otherwise("256"),
        F.lit(");lr=constant("), F.when(F.col("lo") < first, "0.1").when(F.col("lo") < second, "0.01").otherwise("0.001"), F.lit(")"),
    )
    return spans.select("study", (first * 1_000_000 + F.col("b")).alias("trial"), F.col("ord").cast("long").alias("ord"), cfg.alias("cfg"), (F.element_at("cuts", F.col("ord") + 2) - F.col("lo")).alias("steps"))


def sample(trials: DataFrame, n: int, seed: int) -> DataFrame:
    """n trials in a seeded order that any engine repeats (md5)."""
    return trials.orderBy(F.md5(F.concat(F.lit(f"{seed}-"), F.col("trial").cast("string")))).limit(n)


def _steps(a: int, b: int, n: int, init: float = 0.1) -> list[H.Piece]:
    return H.step_decay(init, 0.1, [a, b], n)


def families_w4() -> dict[str, list]:
    """448 trials of 120 epochs: 28 learning rates, 2 batch sizes, 4 optimizer and momentum pairs, 2 decays."""
    n = 120
    ab = [(60, 90), (60, 110), (80, 100), (80, 110), (90, 105), (90, 110), (100, 110), (100, 115)]
    lr = [_steps(a, b, n) for a, b in ab]
    lr += [H.warmup(5, 0.1, H.multi_value([0.1, 0.01, 0.001], [a - 5, b - 5], n - 5)) for a, b in ab]
    lr += [H.warmup(5, 0.1, H.exponential(0.1, g, n - 5)) for g in (0.9, 0.93, 0.95, 0.97)]
    lr += [H.warmup(10, 0.1, H.cosine_restarts(0.1, t, n - 10)) for t in (10, 20, 30, 40)]
    lr += [H.cyclic(0.001, 0.1, u, n) for u in (10, 15, 20, 30)]
    bs = [H.constant(128, n), H.multi_value([128, 256], [90], n)]
    om = [H.constant(-1, n), H.constant(0, n), H.constant(0.9, n), H.multi_value([0.7, 0.8, 0.9], [40, 80], n)]  # -1: adam, without momentum
    return {"lr": lr, "bs": bs, "momentum": om, "decay": [H.constant(1e-4, n), H.constant(1e-3, n)]}


def families_w6() -> dict[str, list]:
    """240 trials of 120 epochs: 60 learning rates, 2 batch sizes, 2 cutout sizes."""
    n = 120
    ab = [(a, b) for a in (50, 60, 70, 80, 90, 100) for b in (105, 108, 111, 114)]
    lr = [_steps(a, b, n) for a, b in ab]
    lr += [H.warmup(10, 0.1, H.multi_value([0.1, 0.01, 0.001], [a - 10, b - 10], n - 10)) for a, b in ab]
    lr += [H.warmup(10, 0.1, H.exponential(0.1, g, n - 10)) for g in (0.9, 0.93, 0.95, 0.97)]
    lr += [H.warmup(10, 0.1, H.cosine_restarts(0.1, t, n - 10)) for t in (10, 20, 30, 40)]
    lr += [H.cyclic(0.001, 0.1, u, n) for u in (10, 15, 20, 30)]
    return {"lr": lr, "bs": [H.constant(128, n), H.multi_value([128, 256], [30], n)], "cutout": [H.constant(16, n), H.multi_value([16, 18, 20], [30, 60], n)]}


def families_w7() -> dict[str, list]:
    """40 trials of 270 units of 100 steps: 10 learning rates, 4 input lengths."""
    n = 270
    lr = [H.linear(i * 1e-5, 0.0, 300, n) for i in range(1, 6)]
    lr += [H.warmup(30, i * 1e-5, H.linear(i * 1e-5, 0.0, 300, n - 30)) for i in range(1, 6)]
    return {"lr": lr, "length": [H.constant(384, n), *[H.multi_value([384, 512], [m], n) for m in (126, 186, 240)]]}


def families_w8(i: int) -> dict[str, list]:
    """144 trials of study i, much shared between studies."""
    n = 120
    ab = [(30 + 15 * a + i, 80 + 10 * b) for a in range(3) for b in range(4)]
    lr = [_steps(a, b, n) for a, b in ab] + [H.warmup(5, 0.1, H.multi_value([0.1, 0.01, 0.001], [a - 5, b - 5], n - 5)) for a, b in ab]
    lr += [H.warmup(5, 0.1, H.exponential(0.1, g, n - 5)) for g in (0.9, 0.92, 0.94, 0.95, 0.96, 0.97)]
    lr += [H.cyclic(0.001, 0.1, u, n) for u in (10, 12, 15, 20, 25, 30)]
    return {"lr": lr, "bs": [H.constant(128, n), *[H.multi_value([128, 256], [m], n) for m in (20 + i, 40 + i, 60 + i)]]}


def families_w9(i: int) -> dict[str, list]:
    """144 trials of study i, little shared between studies."""
    n, iv = 120, round(0.05 + 0.01 * i, 2)
    ab = [(20 + 10 * a + i, 60 + 10 * b) for a in range(3) for b in range(3)]
    lr = [_steps(a, b, n, x) for x in (0.1, iv / 2) for a, b in ab]
    lr += [H.warmup(5, x, H.exponential(x, g, n - 5)) for x in (0.1, iv) for g in (0.9, 0.93, 0.96)]
    lr += [H.cyclic(0.001, iv, u, n) for u in range(6, 29, 2)]
    return {"lr": lr, "bs": [H.multi_value([x, 256], [m], n) for x in (64, 128) for m in (20, 40)]}


def families_small() -> dict[str, list]:
    """16 trials of 64 steps, for studies that train round by round."""
    n = 64
    ab = [(16, 32), (16, 48), (32, 48)]
    lr = [_steps(a, b, n, 0.5) for a, b in ab] + [H.warmup(8, 0.5, H.multi_value([0.5, 0.05, 0.005], [a - 8, b - 8], n - 8)) for a, b in ab]
    lr += [H.warmup(8, 0.5, H.exponential(0.5, g, n - 8)) for g in (0.9, 0.97)]
    return {"lr": lr, "bs": [H.constant(32, n), H.multi_value([32, 64], [24], n)]}


def w4(spark: SparkSession) -> DataFrame:
    return grid(spark, "w4", families_w4())


def w6(spark: SparkSession) -> DataFrame:
    return grid(spark, "w6", families_w6())


def w7(spark: SparkSession) -> DataFrame:
    return grid(spark, "w7", families_w7())


def w8(spark: SparkSession, studies: int) -> DataFrame:
    return reduce(DataFrame.unionByName, [grid(spark, str(i), families_w8(i)) for i in range(studies)])


def w9(spark: SparkSession, studies: int) -> DataFrame:
    return reduce(DataFrame.unionByName, [grid(spark, str(i), families_w9(i)) for i in range(studies)])


def small(spark: SparkSession) -> DataFrame:
    return grid(spark, "small", families_small())
