"""Helpers that the operators share: scratch tables, Arrow text columns, hashing, components."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import re
import tempfile
import uuid
from functools import lru_cache, wraps

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_SPACE = r"[\x20\x09-\x0D]+"
#: Text bytes that one Python step holds at a time.
SLICE_BYTES = 4 << 20


def scratch_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a local one where that is unset and all runs in this process (tests)."""
    sc = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not root:
        if not re.match(r"local(\[|$)", sc.master):  # each machine of a cluster would have a folder of its own
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="orderproof-")
        sc.setCheckpointDir(root)
    return str(root).rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path below the shared folder, removed when the driver ends."""
    path = f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex}"
    atexit.register(_delete, spark, path)
    return path


def staged(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """df written as Parquet to the shared folder and read again: lineage is cut and losses of executors don't recompute it."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    w = df.write.mode("overwrite").option("compression", "zstd")
    (w.partitionBy(*partition_by) if partition_by else w).parquet(path)
    swept(spark)
    if _made is not None:
        _made.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


#: Rows of a small table, of a few numbers each, up to which it is broadcast; beyond, the join shuffles.
BROADCAST_ROWS = 1_000_000


def small(df: DataFrame) -> DataFrame:
    """df, marked for broadcast if its rows, which are counted, are few. For staged tables of a few numbers a row."""
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


_made: list[str] | None = None  # scratch tables of the pipeline stage that is being put together
_left: dict[int, list[str]] = {}  # those of stages that were, by the stage's place


def stage_of_pipeline(place: int):
    """A stage whose scratch tables go when the stage at the next place begins: by then its result has been written and read again.
    Tables of anything else aren't touched."""

    def wrap(f):
        @wraps(f)
        def run(spark, docs, sf_dir):
            global _made
            for path in _left.pop(place - 1, []):
                _delete(spark, path)
            swept(spark)
            outer, _made = _made, []
            try:
                return f(spark, docs, sf_dir)
            finally:
                _left.setdefault(place, []).extend(_made)
                _made = outer

        return run

    return wrap


def swept(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of finished jobs now; it does so when the driver collects their handles as garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def released(*tables: DataFrame, below: str = "") -> None:
    """Deletes staged tables, or the folder `below` in them, that nothing reads any more."""
    for t in tables:
        _delete(t.sparkSession, f"{t._scratch}/{below}".rstrip("/"))


def plan_bytes(df: DataFrame) -> int:
    """Catalyst's estimate of the bytes df is made of."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def trim() -> None:
    """Gives back memory that this worker has freed: workers stay for later stages, beside those that these start."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def trimmed(run):
    """A function over batches that gives memory back after each slice it yields and at its end."""

    @wraps(run)
    def over(batches):
        for k, out in enumerate(run(batches)):
            yield out
            if k % 8 == 7:
                trim()
        trim()

    return over


def text_slices(batch: pa.RecordBatch, column: str = "text", limit: int = SLICE_BYTES):
    """Consecutive row slices of a batch with about `limit` bytes of text each; a longer single text is a slice of its own."""
    if not batch.num_rows:
        return
    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends = np.cumsum(size)
    start = 0
    while start < batch.num_rows:
        before = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, before + limit, "right")))
        yield batch.slice(start, stop - start)
        start = stop


def text_buffers(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets from 0 and UTF-8 bytes of texts; null is empty."""
    text = pc.fill_null(text, "").cast(pa.large_string())
    if not len(text):
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    off = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
    data = np.frombuffer(text.buffers()[2], np.uint8)[off[0] : off[-1]] if off[-1] > off[0] else np.zeros(0, np.uint8)
    return off - off[0], data


def from_buffers(offsets: np.ndarray, data: np.ndarray) -> pa.Array:
    """The strings that lie between consecutive offsets."""
    return pa.LargeStringArray.from_buffers(len(offsets) - 1, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(np.ascontiguousarray(data)))


def lowered(text: pa.Array) -> pa.Array:
    """A-Z in lower case. pyarrow's own kernel spoils multi-byte characters in slices, so the bytes are shifted here."""
    off, data = text_buffers(text)
    return from_buffers(off, data + np.uint8(32) * ((data >= 65) & (data <= 90)))


def words_of(text: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """Flat words of lower-cased (A-Z) texts, split at ASCII white space, and the row of each word; null is empty."""
    lists = pc.ascii_split_whitespace(lowered(text))
    counts = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    rows = np.repeat(np.arange(len(text)), counts)
    flat = lists.flatten()
    full = pc.not_equal(flat, "")
    keep = full.to_numpy(zero_copy_only=False)
    return flat.filter(full), rows[keep]


def mix64(x: np.ndarray) -> np.ndarray:
    """A finaliser over unsigned 64-bit integers (multiply, shift, xor)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def word_hashes(words: pa.Array, seed: int = 0) -> np.ndarray:
    """64-bit hash of each word; every distinct word of the array is hashed once."""
    import xxhash

    if not len(words):
        return np.zeros(0, np.uint64)
    d = words.dictionary_encode()
    h = np.fromiter((xxhash.xxh3_64_intdigest(w.as_buffer() if w.is_valid else b"", seed) for w in d.dictionary.cast(pa.large_binary())), np.uint64, len(d.dictionary))
    return h[d.indices.to_numpy()]


_STEP = 0x9E3779B97F4A7C17  # 3 modulo 4, so that two places' factors share few low bits
_PLACES = 1 << 16
#: Text bytes hashed at a time.
HASH_BYTES = 2 << 20


@lru_cache(maxsize=1)
def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A 64-bit number for each byte (A-Z as a-z), the step's powers, and which bytes are ASCII white space."""
    of = mix64(np.arange(1, 257, dtype=np.uint64))
    of[65:91] = of[97:123]
    of[[32, *range(9, 14)]] = 0
    power = np.full(_PLACES, _STEP, np.uint64)
    power[0] = 1
    space = np.zeros(256, bool)
    space[[32, *range(9, 14)]] = True
    return of, np.cumprod(power, dtype=np.uint64), space


def hashed_words(text: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, 64-bit hash, first byte in the array's bytes) of each word of lower-cased (A-Z) texts, split at ASCII white space, in
    order; null is empty. A word's hash is a polynomial over numbers that stand for its bytes, mixed; it's computed without making
    the word."""
    off, data = text_buffers(text)
    of, power, white = _tables()
    first = off[:-1][np.diff(off) > 0]
    out_start, out_hash = [], []
    a, n = 0, len(data)
    while a < n:
        b = min(a + HASH_BYTES, n)
        while b < n and not white[data[b]]:  # a word isn't cut
            ahead = white[data[b : b + HASH_BYTES]]
            b += int(np.argmax(ahead)) if ahead.any() else len(ahead)
        part = data[a:b]
        inside = ~white[part]
        after = np.empty(len(part), bool)  # behind white space or at the begin of a text
        after[0] = True
        np.logical_not(inside[:-1], out=after[1:])
        x, y = np.searchsorted(first, [a, b])
        after[first[x:y] - a] = True
        start = np.flatnonzero(inside & after)
        if len(start):
            size = np.diff(start, append=len(part))  # with the white space behind the word, which stands for 0
            value = of[part[start[0] :]]
            place = np.arange(start[0], len(part), dtype=np.int32) - np.repeat(start.astype(np.int32), size)
            value *= power[place if size.max() <= _PLACES else place & (_PLACES - 1)]
            if size.max() > _PLACES:
                value *= np.array([pow(_STEP, _PLACES * k, 1 << 64) for k in range(int(size.max()) // _PLACES + 1)], np.uint64)[place // _PLACES]
            out_hash.append(mix64(np.add.reduceat(value, start - start[0])))
            out_start.append(start + a)
        a = b
    start = np.concatenate(out_start) if out_start else np.zeros(0, np.int64)
    h = np.concatenate(out_hash) if out_hash else np.zeros(0, np.uint64)
    return np.searchsorted(off, start, "right") - 1, h, start


def components(edges: DataFrame, name: str = "cc") -> DataFrame:
    """Connected components of edges (a, b: long) as (node, component), the component being its smallest node.

    Alternates hooking of larger neighbours and of smaller ones to each node's minimum until nothing moves; each round is
    written out. Every aggregate is partial before its shuffle, so a node with very many neighbours costs no more than others.
    """
    e = staged(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u != v").distinct(), name)
    while True:
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        down = staged(large.distinct(), name)
        low = down.groupBy("u").agg(F.min("v").alias("m"))
        joined = down.join(low, "u").select("u", "v", "m")
        nxt = staged(joined.select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).filter("u != v").distinct(), name)
        released(e, down)
        e = nxt
        told = e.agg(F.count("*").alias("n"), F.countDistinct("u").alias("k")).head()
        roots = e.select(F.col("u").alias("v")).distinct()
        if told.n == told.k and not e.join(roots, "v", "left_semi").limit(1).count():
            return e.select(F.col("u").alias("node"), F.col("v").alias("component"))


def free(name: str, columns) -> str:
    """`name`, with as many underscores before it as make it differ from all columns."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def addressed(df: DataFrame) -> tuple[DataFrame, str, str]:
    """(df with two more columns, their names): the file and the place in it of each row, the same however the files are split.

    What isn't a plain selection from files is written down first.
    """
    plan = df._jdf.queryExecution().analyzed()
    plain = plan.deterministic()
    while plan.nodeName() in ("Project", "Filter", "SubqueryAlias"):
        plan = plan.children().head()
        plain = plain and plan.deterministic()
    if not plain or plan.nodeName() not in ("LogicalRelation", "Relation") or any(c.lower() == "_metadata" for c in df.columns):
        if any(c.lower() == "_metadata" for c in df.columns):  # a user's own column hides the files' one
            file, row = free("file", df.columns), free("row", df.columns)
            return staged(df.withColumns({file: F.lit(0).cast("long"), row: F.monotonically_increasing_id()}), "rows"), file, row
        df = staged(df, "rows")
    file, row = free("file", df.columns), free("row", df.columns)
    meta = df.metadataColumn("_metadata")
    return df.select("*", F.xxhash64(meta["file_path"]).alias(file), meta["row_index"].alias(row)), file, row


def packed(x: np.ndarray) -> bytes:
    """Integers as offsets from the smallest one, in as few bytes each as the largest takes."""
    x = x.astype(np.int64)
    low = int(x.min(initial=0)) if len(x) else 0
    off = (x - low).astype(np.uint64)
    width = max(1, (int(off.max(initial=0)).bit_length() + 7) // 8)
    body = off.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width]
    return np.array([low, width], "<i8").tobytes() + body.tobytes()


def unpacked(raw: bytes) -> np.ndarray:
    low, width = np.frombuffer(raw, "<i8", 2).tolist()
    out = np.zeros(((len(raw) - 16) // width, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8, offset=16).reshape(-1, width)
    return out.view("<i8").ravel() + low
