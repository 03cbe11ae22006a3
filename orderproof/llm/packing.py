"""Packing along a space-filling curve.

Each document's token counts, hashed to a short vector, are projected to a few dimensions; its place on the Hilbert curve through
these, standardised over all documents, orders the corpus. Ranges of the curve are packed side by side: documents are laid
end to end and cut every `length` tokens, so neighbours on the curve share sequences. What is left at a range's end is cut
into sequences whose lengths are powers of two, which need no padding.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm import bpe
from orderproof.llm.common import mix64, staged, text_slices, trimmed

WIDTH, DIMS, BITS = 256, 4, 10
#: Documents laid out at a time.
ROWS = 500
PIECES = "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long"


def hilbert(points: np.ndarray, bits: int) -> np.ndarray:
    """Place on the Hilbert curve of integer points (n, dims) of `bits` bits each, by axis transposition."""
    x = points.astype(np.int64).T.copy()
    dims = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        for i in range(dims):
            high = (x[i] & q) != 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & (q - 1))
            x[0] ^= np.where(high, q - 1, swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t ^= np.where((x[-1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= t
    key = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            key = key << 1 | (x[i] >> b) & 1
    return key


def vectors(count: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Projections (n, DIMS) of the documents' hashed count vectors of length 1."""
    bucket = (mix64(np.arange(1 << 17)) >> np.uint64(56)).astype(np.int64)
    row = np.repeat(np.arange(len(count)), count)
    v = np.sqrt(np.bincount(row * WIDTH + bucket[ids], minlength=len(count) * WIDTH).reshape(-1, WIDTH))
    v /= np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)
    return v @ np.random.default_rng(1).normal(size=(WIDTH, DIMS))


def _tokenised(make, end: int, kind: str):
    def run(batches):
        enc = make()
        for batch in batches:
            for part in text_slices(batch):
                n, ids = bpe.encode_texts(part.column("text"), enc)
                p = vectors(n, ids)
                closed = np.insert(ids, np.cumsum(n), end)
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), bpe.binaries(n + 1, closed, kind), pa.FixedSizeListArray.from_arrays(pa.array(p.ravel()), DIMS).cast(pa.list_(pa.float64()))], ["id", "ids", "p"]
                )
        enc.known.clear()  # the worker stays for other stages

    return run


def lay_out(docs, length: int, first: int):
    """Pieces (doc, start, size, sequence, offset) for (doc, tokens) in order; the last, short sequence is cut by powers of two.

    `docs` gives batches of (doc index, size) arrays; a batch's pieces come with the batch after it at the latest.
    """
    sequence, open_ = first, []  # pieces of the sequence that isn't full: doc, start, size
    filled = 0
    for doc, size in docs:
        out = []
        for d, n in zip(doc.tolist(), size.tolist(), strict=True):
            start = 0
            while start < n:
                take = min(n - start, length - filled)
                open_.append((d, start, take))
                filled += take
                start += take
                if filled == length:
                    at = 0
                    for x, s, k in open_:
                        out.append((x, s, k, sequence, at))
                        at += k
                    sequence, open_, filled = sequence + 1, [], 0
        yield out, {x[0] for x in open_}
    out = []
    at, room = 0, 0
    for x, s, k in open_:
        while k:
            if not room:
                room, at, sequence = 1 << (filled.bit_length() - 1), 0, sequence + 1
                filled -= room
            take = min(k, room)
            out.append((x, s, take, sequence - 1, at))
            s, k, at, room = s + take, k - take, at + take, room - take
    yield out, set()


def _packed(length: int, kind: str):
    def run(batches):
        held: dict[int, tuple] = {}  # documents with pieces to come: id, bytes
        width = np.dtype(kind).itemsize
        count = 0

        def sizes():
            nonlocal count
            for batch in batches:
                for a in range(0, batch.num_rows, ROWS):  # few at a time, whose bytes are held as Python's
                    part = batch.slice(a, ROWS)
                    ids, raw = part.column("id").to_pylist(), part.column("ids").to_pylist()
                    at = np.arange(count, count + len(ids))
                    held.update(zip(at.tolist(), zip(ids, raw, strict=True), strict=True))
                    count += len(ids)
                    yield at, np.fromiter((len(b) // width for b in raw), np.int64, len(raw))

        for out, waiting in lay_out(sizes(), length, TaskContext.get().partitionId() << 32):
            cols = [[], [], [], [], [], [], []]
            for d, s, k, sequence, at in out:
                i, raw = held[d]
                body = np.frombuffer(raw[s * width : (s + k) * width], kind).astype("<u4").tobytes()
                for c, v in zip(cols, (i, s, k, body, len(raw) // width, sequence, at), strict=True):
                    c.append(v)
            for d in [d for d in held if d not in waiting]:
                del held[d]
            for a in range(0, len(out), 2000):
                part = [c[a : a + 2000] for c in cols]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary() if k == 3 else pa.int64()) for k, c in enumerate(part)], ["doc_id", "start", "length", "ids", "doc_tokens", "sequence_id", "offset"])

    return trimmed(run)


def pack(docs: DataFrame, make, end: int = 1, length: int = 2048, vocabulary: int = 50_257, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces (doc_id, start, length, ids, doc_tokens, sequence_id, offset), ids as little-endian unsigned 32-bit integers.

    `make` returns a bpe.Encoder on a worker; `end` follows each document's ids. Every id is in one piece, sequences have
    `length` tokens or a smaller power of two. Null texts are empty: one piece with `end` alone. Repeated and null ids are
    documents of their own. Other columns aren't read.
    """
    kind = "<u2" if vocabulary <= 1 << 16 else "<u4"
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    rows = staged(texts.mapInArrow(trimmed(_tokenised(make, end, kind)), "id long, ids binary, p array<double>"), "tokens")
    told = rows.select(*(f(F.get("p", F.lit(d))).alias(f"{n}{d}") for d in range(DIMS) for n, f in (("m", F.avg), ("s", F.stddev_pop)))).head()
    mean, spread = (np.array([told[f"{n}{d}"] or 0.0 for d in range(DIMS)]) for n in "ms")

    @F.arrow_udf("long")
    def place(p: pa.Array) -> pa.Array:
        x = (p.flatten().to_numpy(zero_copy_only=False).reshape(-1, DIMS) - mean) / np.maximum(spread, 1e-12)
        return pa.array(hilbert(np.clip((1 + np.tanh(0.8 * x)) * (1 << (BITS - 1)), 0, (1 << BITS) - 1), BITS))

    keyed = rows.select("id", "ids", place("p").alias("key"))
    return keyed.repartitionByRange("key", "id").sortWithinPartitions("key", "id").select("id", "ids").mapInArrow(_packed(length, kind), PIECES)


def byte_bpe_50k():
    import public_tokenizers as public

    return bpe.special_encoder(public.path("byte_bpe_50k.json"), public.path("byte_bpe_50k.tiktoken"), public.PATTERN)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), byte_bpe_50k)
    return pieces.select("doc_id", "start", "length", digest(F.col("ids")).alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def digest(ids: Column) -> Column:
    return F.crc32(ids)
