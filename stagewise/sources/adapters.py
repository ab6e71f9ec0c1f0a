"""Given tables read as pieces of trials: (study, trial, ord, cfg, steps).

``ord`` is a struct whose order is the order of a trial's pieces; ties would make the order
unclear, so it holds every column that can differ.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TRIAL_PIECES = "study string, trial bigint, ord, cfg string, steps bigint"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def orders(spark: SparkSession, sf_dir: str, value: str = "priority", study: F.Column | None = None) -> DataFrame:
    """A customer's orders by date: value is the priority's initial, the status, or both; F, O, P last 10, 20, 30 steps."""
    o = table(spark, sf_dir, "orders")
    initial, status = F.substring("o_orderpriority", 1, 1), F.col("o_orderstatus")
    cfg = {"priority": initial, "status": status, "both": F.concat(initial, status)}[value]
    steps = F.when(status == "F", 10).when(status == "O", 20).otherwise(30).cast("long")
    return o.select(
        (study if study is not None else F.lit("all")).alias("study"),
        F.col("o_custkey").cast("long").alias("trial"),
        F.struct("o_orderdate", "o_orderkey").alias("ord"),
        cfg.alias("cfg"),
        steps.alias("steps"),
    )


def blocks(spark: SparkSession, sf_dir: str, size: int) -> DataFrame:
    """Studies of so many neighbouring customers: a customer's orders are one sequence of learning rates, urgent ones last 150 steps, others 100."""
    o, status = table(spark, sf_dir, "orders"), F.col("o_orderstatus")
    return o.select(
        F.coalesce(F.expr(f"cast(o_custkey div {size} as string)"), F.lit("-")).alias("study"), F.col("o_custkey").cast("long").alias("trial"), F.struct("o_orderdate", "o_orderkey").alias("ord"),
        F.when(status == "F", "0.1").when(status == "O", "0.05").otherwise("0.01").alias("cfg"),
        F.when(F.col("o_orderpriority").startswith("1"), 150).otherwise(100).cast("long").alias("steps"),
    )


def pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A customer's orders as trials of one study: 100 steps by the order's status, 100 by its priority."""
    o, status = table(spark, sf_dir, "orders"), F.col("o_orderstatus")
    initial = F.substring("o_orderpriority", 1, 1)
    first = F.when(status == "F", "0.1").when(status == "O", "0.01").otherwise("0.05")
    second = F.when(initial == "1", "0.1").when(initial == "2", "0.05").when(initial == "3", "0.01").when(initial == "4", "0.005").otherwise("0.001")
    p = o.select(
        F.coalesce(F.col("o_custkey").cast("string"), F.lit("-")).alias("study"), F.col("o_orderkey").cast("long").alias("trial"),
        F.posexplode(F.array(first, second)).alias("ord", "cfg"),
    )
    return p.withColumn("steps", F.lit(100).cast("long"))


def years(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A customer's orders of one year: config is the priority's initial; 10, 15 or 20 steps, by the order's key."""
    o = table(spark, sf_dir, "orders")
    return o.select(
        F.lit("all").alias("study"), (F.col("o_custkey").cast("long") * 10_000 + F.year("o_orderdate")).alias("trial"), F.struct("o_orderdate", "o_orderkey").alias("ord"),
        F.concat(F.lit("H"), F.substring("o_orderpriority", 1, 1)).alias("cfg"), (10 + 5 * (F.col("o_orderkey") % 3)).cast("long").alias("steps"),
    )


def with_customer(pieces: DataFrame, spark: SparkSession, sf_dir: str, study: str) -> DataFrame:
    """Studies by an attribute of the trial's customer; the customer table joins on the trial's key."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("trial"), F.col(study).cast("string").alias("study"))
    return pieces.drop("study").join(c, "trial").select("study", "trial", "ord", "cfg", "steps")


def lineitem(spark: SparkSession, sf_dir: str, fine: bool = False) -> DataFrame:
    """An order's lines: config is return flag and line status, in the fine form discount and tax too; steps are the quantity."""
    t = table(spark, sf_dir, "lineitem")
    cfg = [F.col("l_returnflag"), F.col("l_linestatus")]
    if fine:
        cfg += [F.format_string("%d", F.round(F.col(x) * 100).cast("int")) for x in ("l_discount", "l_tax")]
    tie = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice"]
    if fine:
        tie += ["l_returnflag", "l_linestatus", "l_discount", "l_tax"]
    else:
        tie += ["l_returnflag", "l_linestatus"]
    return t.select(
        F.lit("all").alias("study"), F.col("l_orderkey").cast("long").alias("trial"), F.struct(*tie).alias("ord"),
        F.concat_ws("|", *cfg).alias("cfg"), F.col("l_quantity").cast("long").alias("steps"),
    )


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user's day: the sequence of event types, 10 steps each."""
    t = table(spark, sf_dir, "events")
    day = F.date_diff(F.col("ts").cast("date"), F.lit("1970-01-01").cast("date"))
    return t.select(
        F.lit("all").alias("study"), (F.col("user_id").cast("long") * 100_000 + day).alias("trial"),
        F.struct("ts", "event_id").alias("ord"), F.col("event_type").alias("cfg"), F.lit(10).cast("long").alias("steps"),
    )


TRIAL_FILE = "study string, trial bigint, ord bigint, cfg string, steps bigint"


def trial_files(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """Pieces of trials that clients left as JSON or CSV files; a row that does not read as a piece is left out and can be had by ``broken_files``."""
    return _files(spark, path, kind).where("_corrupt_record is null and trial is not null and steps is not null").drop("_corrupt_record")


def broken_files(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """The rows that :func:`trial_files` leaves out, as text."""
    return _files(spark, path, kind).where("_corrupt_record is not null or trial is null or steps is null").select("_corrupt_record", "study", "trial")


def _files(spark: SparkSession, path: str, kind: str) -> DataFrame:
    read = spark.read.schema(TRIAL_FILE + ", _corrupt_record string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record")
    return read.json(path) if kind == "json" else read.option("header", "true").csv(path)


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A conversation's turns: config is the role, 10 steps each."""
    t = table(spark, sf_dir, "conversations")
    return t.select(
        F.lit("all").alias("study"), F.col("conv_id").cast("long").alias("trial"), F.struct("turn", "role").alias("ord"),
        F.col("role").alias("cfg"), F.lit(10).cast("long").alias("steps"),
    )
