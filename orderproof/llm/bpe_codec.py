"""Byte-level BPE by overlapping chunks.

A long text is cut into chunks of `chunk` characters, each read `overlap` characters into the next one, and every chunk is cut into
pre-tokens on its own, in parallel. Two chunks agree from the first boundary that both have in their overlap: the pattern only
looks ahead, so equal boundaries mean equal pre-tokens from there on. Only the boundaries in overlaps meet, by text, and tell where
chunks are stitched; each chunk then encodes its own stretch between two stitches, in parallel again. Where an overlap holds no
common boundary (a pre-token longer than it) the chunks on both sides are encoded as one stretch.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm import bpe
from orderproof.llm.common import staged, text_slices, trimmed

CHUNK, OVERLAP = 32_768, 1_024
#: Text bytes encoded, and ids decoded, at a time.
PART_BYTES, PART_IDS = 1 << 20, 1 << 18


def boundaries(pattern, text: str) -> np.ndarray:
    """Starts of the pre-tokens of a text, and its length."""
    return np.fromiter([0, *(m.end() for m in pattern.finditer(text))], np.int64)


def seams(body: str, pattern, chunk: int, overlap: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Certain boundaries of a chunk in the overlap with the one before it and with the one after it, relative to the overlap's begin,
    and which of the first lie before an ASCII space behind another ASCII character: there any engine for the pattern cuts."""
    at = boundaries(pattern, body)[:-1]  # the last pre-token may go on behind the chunk, but its start is certain
    head = at[(at > 0) & (at <= overlap)]
    sure = np.array([body[i] == " " and "!" <= body[i - 1] <= "~" for i in head.tolist()], bool)
    return head, at[at > chunk] - chunk, sure


def stitches(count: int, heads: dict[int, np.ndarray], tails: dict[int, np.ndarray], sure: dict[int, np.ndarray], chunk: int) -> list[tuple[int, int]]:
    """(first chunk, place in the whole text) of each stretch of a text of `count` chunks. A chunk that wasn't stitched to the one
    before it has no certain boundaries itself, but for those before a space."""
    out, certain = [(0, 0)], True
    for k in range(1, count):
        common, i, _ = np.intersect1d(heads[k], tails[k - 1], assume_unique=True, return_indices=True)
        best = common[sure[k][i]] if sure[k][i].any() else common if certain else common[:0]
        certain = len(best) > 0
        if certain:
            out.append((k, k * chunk + int(best[0])))
    return out


def encode(docs: DataFrame, path: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids) for every row of docs, ids as little-endian unsigned 32-bit integers, as the vocabulary's own library gives
    them without special tokens. Null texts are empty. Repeated and null ids are rows of their own; other columns aren't read.

    Texts of one chunk are encoded where they are read. The chunks of longer ones are dealt out, and their ids meet again by text.
    """
    import regex

    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), F.monotonically_increasing_id().alias("row"))

    def short(batches):
        enc = bpe.encoder(path, pattern)
        for batch in batches:
            for part in text_slices(batch, limit=PART_BYTES):
                ids = [np.array(enc.encode(t.as_py()), "<u4").tobytes() for t in part.column("text")]
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(ids, pa.binary())], ["id", "ids"])

    def split(batches):
        for batch in batches:
            for i, t, row in zip(*(batch.column(c) for c in ("id", "text", "row")), strict=True):
                text = t.as_py()
                for k, a in enumerate(range(0, len(text), chunk)):
                    yield pa.RecordBatch.from_arrays([pa.array([i.as_py()], pa.int64()), pa.array([row.as_py()]), pa.array([k]), pa.array([text[a : a + chunk + overlap]])], ["id", "row", "k", "body"])

    def cut(batches):
        compiled = regex.compile(pattern)
        for batch in batches:
            got = [seams(b.as_py(), compiled, chunk, overlap) for b in batch.column("body")]
            told = [pa.array([g[i].tolist() for g in got], pa.list_(t)) for i, t in enumerate((pa.int64(), pa.int64(), pa.bool_()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *told], ["id", "row", "k", "body", "head", "tail", "sure"])

    def plan(table: pa.Table) -> pa.Table:
        k = table["k"].to_pylist()
        head, tail, sure = ({a: np.array(b, t) for a, b in zip(k, table[c].to_pylist(), strict=True)} for c, t in (("head", np.int64), ("tail", np.int64), ("sure", bool)))
        first = stitches(len(k), head, tail, sure, chunk)
        # chunk k's stretch begins at `start`; it needs the chunks up to `last`, and ends at `stop` (null: with the text)
        stretch = [(a, s, n[1] if n else None, (n[0] if n else len(k)) - 1) for (a, s), n in zip(first, [*first[1:], None], strict=True)]
        rows = [(a, b, s, e) for a, s, e, last in stretch for b in range(a, last + 1)]
        return pa.table([pa.array([table["row"][0].as_py()] * len(rows), pa.int64()), *(pa.array([r[i] for r in rows], pa.int64()) for i in (1, 0, 2, 3))], ["row", "k", "first", "start", "stop"])

    def one(batches):
        """Stretches of a single chunk."""
        enc = bpe.encoder(path, pattern)
        for batch in batches:
            out = []
            for body, first, start, stop in zip(*(batch.column(c) for c in ("body", "first", "start", "stop")), strict=True):
                base = first.as_py() * chunk
                out.append(np.array(enc.encode(body.as_py()[start.as_py() - base : stop.as_py() - base if stop.is_valid else None]), "<u4").tobytes())
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("id", "row", "first")), pa.array(out, pa.binary())], ["id", "row", "first", "ids"])

    def several(table: pa.Table) -> pa.Table:
        """A stretch over several chunks, whose overlaps hold no common boundary."""
        table = table.sort_by("k")
        text = "".join(b[:chunk] for b in table["body"].to_pylist()[:-1]) + table["body"][-1].as_py()
        base = table["first"][0].as_py() * chunk
        stop = table["stop"][0].as_py()
        ids = bpe.encoder(path, pattern).encode(text[table["start"][0].as_py() - base : None if stop is None else stop - base])
        return pa.table([table["id"][:1], table["row"][:1], table["first"][:1], pa.array([np.array(ids, "<u4").tobytes()], pa.binary())], ["id", "row", "first", "ids"])

    def join(table: pa.Table) -> pa.Table:
        table = table.sort_by("first")
        return pa.table([table["id"][:1], pa.array([b"".join(x.as_buffer().to_pybytes() for x in table["ids"])], pa.binary())], ["id", "ids"])

    long = F.char_length("text") > chunk
    piece = "id long, row long, first long, ids binary"
    dealt = texts.filter(long).mapInArrow(split, "id long, row long, k long, body string").repartition("row", "k")
    chunks = staged(dealt.mapInArrow(trimmed(cut), "id long, row long, k long, body string, head array<long>, tail array<long>, sure array<boolean>"), "chunks")
    stretches = staged(chunks.select("row", "k", "head", "tail", "sure").groupBy("row").applyInArrow(plan, "row long, k long, first long, start long, stop long"), "stretches")
    size = stretches.groupBy("row", "first").agg(F.count("*").alias("n"))
    bodies = chunks.select("id", "row", "k", "body").join(stretches.join(size, ["row", "first"]), ["row", "k"])
    whole = bodies.filter("n = 1").select("id", "row", "body", "first", "start", "stop").mapInArrow(one, piece)
    rest = bodies.filter("n > 1").groupBy("row", "first").applyInArrow(several, piece)
    joined = whole.unionAll(rest).groupBy("row").applyInArrow(join, "id long, ids binary")
    return texts.filter(~long).select("id", "text").mapInArrow(trimmed(short), "id long, ids binary").unionAll(joined)


def decode(rows: DataFrame, path: str, ids_col: str = "ids", out_col: str = "decoded") -> DataFrame:
    """rows with the raw bytes of their ids, one after the other. A null is null."""

    @F.arrow_udf("binary")
    def raw(ids: pa.Array) -> pa.Array:
        start, size, flat = bpe.token_table(path)
        out = []
        for v in ids:
            if not v.is_valid:
                out.append(None)
                continue
            x = np.frombuffer(v.as_buffer(), "<u4")
            parts = []
            for a in range(0, len(x), PART_IDS):
                y = x[a : a + PART_IDS]
                n = size[y]
                at = np.repeat(start[y] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
                parts.append(flat[at].tobytes())
            out.append(b"".join(parts))
        return pa.array(out, pa.binary())

    return rows.withColumn(out_col, raw(ids_col))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as public

    path = public.path("byte_bpe_multi_50k.tiktoken")
    rows = decode(encode(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, public.PATTERN), path)
    return rows.select(
        F.col("id").alias("doc_id"), (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256")
    )
