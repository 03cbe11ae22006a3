"""Streams of client logs: monitoring windows and removal of repeated log lines."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.plans.global_order import ranked, running
from orderproof.schema import OPS, TXNS, History
from orderproof.sources.scratch import folder, written


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", "true").parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def _run(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all there is now and returns what it wrote."""
    spark = stream.sparkSession
    path = f"{folder(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{path}/out/n={number}")

    q = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/state").foreachBatch(write).start()
    q.awaitTermination()
    return spark.read.option("recursiveFileLookup", "true").schema(stream.schema.add("batch", "long")).parquet(f"{path}/out")


def window_reads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Operations by day and kind, as updates of a watermarked window; the last update of each window stands."""
    rows = _events(spark, sf_dir).withWatermark("at", "1 hour").groupBy(F.window("at", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    got = _run(rows, "update")
    last = got.groupBy("w", "event_type").agg(F.max_by("n", "batch").alias("n"))
    return last.select(F.unix_micros("w.start").alias("day_us"), "event_type", "n")


WINDOW_SQL = "SELECT epoch_us(date_trunc('day', ts)) AS day_us, event_type, count(*) AS n FROM events GROUP BY ALL"


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Log lines delivered twice come out once."""
    rows = _events(spark, sf_dir)
    twice = rows.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).withWatermark("at", "30 days").dropDuplicatesWithinWatermark(["event_id"])
    return _run(twice.select("event_id", "at"), "append").agg(F.count("*").alias("n"))


def sliding_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Operations in windows of two hours that begin every hour."""
    rows = _events(spark, sf_dir).withWatermark("at", "1 hour").groupBy(F.window("at", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return _run(rows, "update").groupBy("w").agg(F.max_by("n", "batch").alias("n")).select(F.unix_micros("w.start").alias("from_us"), "n")


SLIDING_SQL = """SELECT epoch_us(date_trunc('hour', ts)) - k * 3600000000 AS from_us, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY ALL"""


def sessions(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """Runs of activity of each user: operations less than `gap` apart."""
    rows = _events(spark, sf_dir).withWatermark("at", "1 hour").groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    # append mode tells a session when the watermark has passed it; what is still open is told by a last pass over the table
    got = _run(rows, "append").select(F.unix_micros("w.start").alias("from_us"), F.unix_micros("w.end").alias("to_us"), "user_id", "n")
    static = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("at", F.col("ts").cast("timestamp"))
    whole = static.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    whole = whole.select(F.unix_micros("w.start").alias("from_us"), F.unix_micros("w.end").alias("to_us"), "user_id", "n")
    return got.unionByName(whole.exceptAll(got))  # users may be null


SESSION_SQL = """WITH o AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS new FROM events),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s FROM o)
SELECT min(t) AS from_us, max(t) + 1800000000 AS to_us, user_id, count(*) AS n FROM g GROUP BY user_id, s"""


def _log(spark: SparkSession, h: History) -> tuple[str, DataFrame]:
    """The history's operations as a folder of log files, a few of which arrive at a time, and a stream over it. Each operation bears its
    transaction's times and status, as a client's recorder tells them when the transaction ends."""
    path = f"{folder(spark)}/log-{uuid.uuid4().hex}"
    rows = h.ops.join(h.txns.select("txn_id", "session_id", "session_pos", "status", "s", "e", "ttype"), "txn_id")
    rows = rows.withColumn("at", F.timestamp_micros("e"))
    rows.repartition(12, "txn_id").write.parquet(path)
    return path, spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 4).parquet(path)


def wr_edges(spark: SparkSession, h: History, horizon: str = "3650 days") -> DataFrame:
    """(src, dst, obj): read dependencies by joining the stream of reads with the stream of writes; a write waits `horizon` for its
    readers, and rows may come as much out of order."""
    _, log = _log(spark, h)
    ok = log.filter("status = 'c'").withWatermark("at", horizon)
    w = ok.filter("kind = 'w'").select(F.col("txn_id").alias("src"), F.col("obj").alias("w_obj"), F.col("ver").alias("w_ver"), F.col("at").alias("w_at"))
    r = ok.filter("kind <> 'w' AND ver IS NOT NULL").select(F.col("txn_id").alias("dst"), "obj", "ver", "at")
    met = r.join(w, F.expr(f"obj = w_obj AND ver = w_ver AND w_at BETWEEN at - INTERVAL {horizon} AND at + INTERVAL {horizon}"))
    return _run(met.filter("src <> dst").select("src", "dst", "obj"), "append").select("src", "dst", "obj").distinct()


def object_versions(spark: SparkSession, h: History) -> DataFrame:
    """(obj, writes, readers): for each object how many versions it had and how many reads it answered, kept as state by object."""
    import pandas as pd

    _, log = _log(spark, h)

    def count(key, frames, state):
        writes, reads = state.get if state.exists else (0, 0)
        for pdf in frames:
            writes += int((pdf.kind == "w").sum())
            reads += int((pdf.kind != "w").sum())
        state.update((writes, reads))
        yield pd.DataFrame({"obj": [key[0]], "writes": [writes], "readers": [reads]})

    rows = log.filter("status = 'c' AND obj IS NOT NULL").select("obj", "kind")
    told = rows.groupBy("obj").applyInPandasWithState(count, "obj string, writes long, readers long", "writes long, reads long", "update", "NoTimeout")
    got = _run(told, "update")
    return got.groupBy("obj").agg(F.max_by("writes", "batch").alias("writes"), F.max_by("readers", "batch").alias("readers"))


def _unpacked(batches):
    """(pred_id, m) of rows (preds): how often each number stands in a batch's rows."""
    import numpy as np
    import pyarrow as pa

    for batch in batches:
        preds, m = np.unique(np.frombuffer(b"".join(batch.column("preds").to_pylist()), np.int32), return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(preds, pa.int32()), pa.array(m, pa.int64())], ["pred_id", "m"])


def matched_predicates(spark: SparkSession, h: History) -> DataFrame:
    """(pred_id, n): matches that predicate reads returned, the stream of reads joined with the static predicates. Of History.returned
    the packed rows are the stream, and are counted by predicate before they meet the state."""
    _, log = _log(spark, h)
    hits = log.filter("kind = 'pr' AND ver IS NOT NULL").select("pred_id", F.lit(1).cast("long").alias("m"))
    if h.returned is not None:
        path = f"{folder(spark)}/log-{uuid.uuid4().hex}"
        h.returned.select("preds").repartition(12).write.parquet(path)
        packed = spark.readStream.schema("preds binary").option("maxFilesPerTrigger", 4).parquet(path)
        hits = hits.unionAll(packed.mapInArrow(_unpacked, "pred_id int, m long"))
    hits = hits.join(h.preds.select("pred_id"), "pred_id").groupBy("pred_id").agg(F.sum("m").alias("n"))
    return _run(hits, "update").groupBy("pred_id").agg(F.max_by("n", "batch").alias("n"))


class OnlineVerifier:
    """Verdicts while the log arrives; a transaction arrives when it ends. They are held until the watermark (the latest end seen, less
    `slack_us`, which must be as long as the longest transaction and the delay together) has passed a gap in which none is open; what lies before the gap is decided as a history of its own, which begins with the versions that
    stand there, and leaves these to the next one. Transactions that began before what is decided and come after it are late: they are
    kept apart and the verdict is provisional from then on.

    What is held is written to the shared folder at each batch: it is as long as transactions overlap, not as the history.
    """

    def __init__(self, spark: SparkSession, slack_us: int = 0):
        self.spark, self.slack, self.decided_to = spark, slack_us, -(1 << 62)
        self.held: DataFrame | None = None
        self.late: list[DataFrame] = []
        self.verdicts: list[tuple] = []
        self.state: DataFrame | None = None  # (obj, ver): last versions of what was decided

    def batch(self, rows: DataFrame, last: bool = False) -> None:
        rows = written(rows)
        behind = rows.filter(F.col("s") < self.decided_to)
        if behind.limit(1).count():
            self.late.append(behind)
        rows = rows.filter(F.col("s") >= self.decided_to)
        held = written(rows if self.held is None else self.held.unionByName(rows))
        top = held.agg(F.max("e")).head()[0]
        if top is None:
            return
        t = held.select("txn_id", "s", "e").distinct()
        bound = top + 1 if last else top - self.slack
        ends = running(t, "s", ["txn_id"], F.col("e"), "max", "upto").select("s", "upto")
        # a gap: everything that began before has ended; the last one before the bound
        gaps = ranked(ends, "s", ["upto"]).select("idx", "s", "upto")
        nxt = gaps.select((F.col("idx") - 1).alias("idx"), F.col("s").alias("next_s"))
        at = gaps.join(nxt, "idx", "left").filter(F.col("upto") <= F.coalesce("next_s", F.lit(bound))).filter(F.col("upto") <= bound).agg(F.max("upto")).head()[0]
        if at is None:
            self.held = held
            return
        done, self.held = held.filter(F.col("e") <= at), written(held.filter(F.col("e") > at))
        self._decide(written(done))
        self.decided_to = at

    def _decide(self, rows: DataFrame) -> None:
        from orderproof.plans import verify

        txns = rows.select(*(c.split()[0] for c in TXNS.split(", "))).distinct()
        ops = rows.select(*(c.split()[0] for c in OPS.split(", ")))
        if self.state is not None:  # versions that stand are the initial ones of this stretch
            old = self.state.withColumnsRenamed({"obj": "o", "ver": "v"})
            ops = ops.join(old, (ops.obj == old.o) & (ops.ver == old.v), "left").withColumn("ver", F.when(F.col("v").isNotNull() & (F.col("kind") != "w"), F.lit(0).cast("long")).otherwise(F.col("ver"))).drop("o", "v")
            stale = rows.filter("kind <> 'w' AND ver = 0").join(self.state.select("obj"), "obj", "left_semi").limit(1).count()
        else:
            stale = 0
        h = History(txns, ops)
        got = verify.verdict(h).head()
        ok = False if stale else got.serializable
        n = txns.count()
        self.verdicts.append((len(self.verdicts), n, ok, "stale_read" if stale else got.reason))
        if ok:
            order = verify.witness(h)
            w = h.ops.filter("kind = 'w'").join(order, "txn_id")
            new = w.groupBy("obj").agg(F.max_by("ver", F.struct("place", "op_seq")).alias("ver"))
            self.state = written(new if self.state is None else new.unionByName(self.state.join(new.select("obj"), "obj", "left_anti")))

    def answer(self) -> tuple[bool, bool]:
        """(serializable so far, provisional)."""
        return all(v[2] for v in self.verdicts), bool(self.late)


def online(spark: SparkSession, h: History, arrivals: int = 4) -> DataFrame:
    """One row: the online verdict of a history whose log arrives in `arrivals` parts by end time, and what it held at most."""
    rows = h.ops.join(h.txns.select("txn_id", "session_id", "session_pos", "status", "s", "e", "ttype"), "txn_id")
    cuts = h.txns.agg(F.percentile_approx("e", [k / arrivals for k in range(1, arrivals)], 10_000)).head()[0] or []
    v = OnlineVerifier(spark, h.txns.agg(F.max(F.col("e") - F.col("s"))).head()[0] or 0)
    edges = [-(1 << 62), *cuts, 1 << 62]
    for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False)):
        v.batch(rows.filter((F.col("e") > a) & (F.col("e") <= b)), last=k == len(edges) - 2)
    ok, provisional = v.answer()
    return spark.createDataFrame([(ok, provisional, sum(x[1] for x in v.verdicts))], "serializable boolean, provisional boolean, decided long")
