"""Exact dedup against a persistent digest index.

The index is a table of (digest, keep_id, batch), bucketed and sorted by digest, so that a sort-merge anti-join of new
digests reads it without a shuffle. New texts are those without a digest there; they are appended.
"""

from __future__ import annotations

import atexit
import contextlib
import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm.common import ASCII_SPACE, scratch_path, staged

#: A digest held by more than one row in so many is joined on its own.
HOT = 1000


def normalised(text: Column) -> Column:
    """Each run of ASCII white space as one space; null as empty."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), ASCII_SPACE, " ")


def digest_of(text: Column) -> Column:
    return F.unhex(F.sha2(normalised(text).cast("binary"), 256))


class DigestIndex:
    """Opens the index at `path`, which is made where there is none. The bucket count is fixed when it is made. One writer at a time: two
    that ingest at once may both append the same new text."""

    def __init__(self, spark: SparkSession, path: str, buckets: int = 64):
        self.spark, self.path = spark, path.rstrip("/")
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/meta/_SUCCESS")
        if p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p):
            buckets = spark.read.parquet(f"{self.path}/meta").head()[0]
        else:
            spark.range(1).select(F.lit(buckets).alias("buckets")).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/meta")
        self.buckets = buckets
        self.name = "digest_index_" + hashlib.md5(self.path.encode()).hexdigest()
        where = f"{self.path}/data".replace("'", "\\'")
        spark.sql(
            f"CREATE TABLE IF NOT EXISTS {self.name} (digest BINARY, keep_id BIGINT, batch STRING) USING parquet "
            f"CLUSTERED BY (digest) SORTED BY (digest) INTO {buckets} BUCKETS LOCATION '{where}'"
        )

    def table(self) -> DataFrame:
        self.spark.catalog.refreshTable(self.name)
        return self.spark.table(self.name)

    def ingest(self, docs: DataFrame, batch: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Deduplicates docs against the index and within themselves, and appends what is new.

        Returns a row per row of docs: id, keep_id (the id that stays for this text: the smallest of the batch that first had
        it), group_size (rows of docs with this text), kept, digest. Null texts are empty, null ids come after all others, and
        of rows with the same id and text one is kept. Repeating a batch under its name changes nothing and returns the same.
        Other columns of docs aren't read.
        """
        rows = staged(docs.select(F.col(id_col).cast("long").alias("id"), digest_of(F.col(text_col)).alias("digest"), F.monotonically_increasing_id().alias("row")), "digests")
        incoming = rows.groupBy("digest").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "row")).alias("first"), F.count("*").alias("group_size"))
        fresh = incoming.join(self.table().select("digest").hint("merge"), "digest", "left_anti")
        fresh.repartition(self.buckets, "digest").select("digest", F.col("first.id").alias("keep_id"), F.lit(batch).alias("batch")).write.insertInto(self.name)
        known = incoming.join(self.table().hint("merge"), "digest").select(
            "digest", "keep_id", "group_size", F.when(F.col("batch") == batch, F.col("first.row")).alias("stays")
        )
        known = staged(known, "known")
        # a digest that more than one row in HOT has is broadcast, of which there are fewer than HOT; the others are merged
        often = F.col("group_size") * HOT > F.lit(rows.count())
        hot = F.broadcast(known.filter(often))
        met = rows.join(hot, "digest").unionByName(rows.join(hot.select("digest"), "digest", "left_anti").join(known.filter(~often), "digest"))
        return met.select("id", "keep_id", "group_size", (F.col("row").eqNullSafe(F.col("stays"))).alias("kept"), "digest")

    def forget(self) -> None:
        """Takes the index out of the catalogue; its files stay."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")


def _gone(index: DigestIndex) -> None:
    with contextlib.suppress(Exception):  # the session may have ended
        index.forget()


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    index = DigestIndex(spark, scratch_path(spark, "digest-index"), buckets=int(spark.conf.get("spark.sql.shuffle.partitions")))
    atexit.register(_gone, index)
    return index.ingest(docs, "documents").select(
        F.col("id").alias("doc_id"), "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256")
    )


ORACLE = r"""
WITH d AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY text_sha256) AS keep_id, count(*) OVER (PARTITION BY text_sha256) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY text_sha256) AS kept, text_sha256
FROM d
"""
