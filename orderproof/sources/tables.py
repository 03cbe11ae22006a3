"""Tables, client logs and the history store."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof import schema
from orderproof.schema import History


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Registers source tables as temporary views for the history texts, under names that no user's view has."""
    for n in names:
        table(spark, sf_dir, n).createOrReplaceTempView(f"orderproof_{n}")


def client_log(spark: SparkSession, path: str, form: str = "json") -> tuple[DataFrame, DataFrame]:
    """(operations, corrupt lines) of a JSON-lines or CSV log with the fixed schema of operations."""
    read = spark.read.schema(schema.OPS + ", _corrupt_record string").option("columnNameOfCorruptRecord", "_corrupt_record").option("mode", "PERMISSIVE")
    rows = read.json(path) if form == "json" else read.option("header", "true").csv(path)
    rows = rows.withColumn("bad", F.col("_corrupt_record").isNotNull() | F.col("txn_id").isNull())
    return rows.filter("not bad").drop("bad", "_corrupt_record"), rows.filter("bad").select("_corrupt_record")


def save(h: History, path: str) -> None:
    """Writes a history, transactions by day and sorted by start so that a time slice prunes files and row groups."""
    day = F.to_date(F.timestamp_micros("s"))
    h.txns.withColumn("day", day).repartition("day").sortWithinPartitions("s").write.mode("overwrite").partitionBy("day").parquet(f"{path}/txns")
    for name in ("ops", "vers", "preds"):
        if (df := getattr(h, name)) is not None:
            df.write.mode("overwrite").parquet(f"{path}/{name}")


def load(spark: SparkSession, path: str) -> History:
    read = lambda name, kind: spark.read.schema(kind).parquet(f"{path}/{name}")

    def maybe(name, kind):
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/{name}")
        there = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)
        return read(name, kind) if there else None

    return History(read("txns", schema.TXNS), read("ops", schema.OPS), maybe("vers", schema.VERS), maybe("preds", schema.PREDS))
