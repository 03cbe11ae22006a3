"""Katz backoff language model (bigrams over unigrams) with Good-Turing discounts and exactly normalised backoff weights.

Tokens are cut and indexed once, in segments of a few million tokens. A segment asks each count table once for every distinct word
and bigram it holds, whatever their frequency: so the hottest one is asked as often as there are segments. The tables are dealt
by hash into buckets whose number follows the input, and are written down; counts come back by segment, in the order of asking. A
word's backoff weight sums over its distinct continuations, each of which one segment owns. Scores are then local to a segment.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm.common import hashed_words, mix64, plan_bytes, released, staged, text_slices

U = np.uint64
BOS, END = U(0x1D8E4E27C47D124F), U(0xE29AD4B97F2E0C35)
SEGMENT_TOKENS = 5_000_000
WAVES = 4
LOW = 48  # bits of a key besides its bucket
ROW = "kind string, seg long, bucket int, id long, held boolean, a binary, b binary"
NAMES = [x.split()[0] for x in ROW.split(", ")]
OWNED = np.uint32(1 << 31)


def _table(rows: list[tuple]) -> pa.Table:
    kinds = [pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.bool_(), pa.binary(), pa.binary()]
    cols = list(zip(*rows, strict=True)) if rows else [[]] * len(kinds)
    return pa.table([pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)], NAMES)


def _packed(key: np.ndarray) -> bytes:
    """Sorted keys of one bucket as differences of their low bits, in as few bytes each as the largest takes (told first)."""
    low = key & U((1 << LOW) - 1)
    gap = np.diff(low, prepend=U(0))
    width = max(1, (int(gap.max(initial=0)).bit_length() + 7) // 8)
    return bytes([width]) + np.ascontiguousarray(gap.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width]).tobytes()


def _unpacked(raw: bytes, bucket: int) -> np.ndarray:
    width = raw[0]
    low = np.frombuffer(raw, np.uint8, offset=1).reshape(-1, width)
    out = np.zeros((len(low), 8), np.uint8)
    out[:, :width] = low
    return np.cumsum(out.view("<u8").ravel().astype(U), dtype=U) | U(bucket) << U(LOW)


def _keys(h: np.ndarray, bits: int) -> np.ndarray:
    return h >> U(64 - LOW - bits)


def bigram_hashes(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return mix64(mix64(first) * U(0x9E3779B97F4A7C15) + second)


@dataclass
class Segment:
    """Token indexes of documents over the sorted distinct word hashes, with the distinct bigrams behind them."""

    size: np.ndarray  # tokens of each document, its end included
    word: np.ndarray  # index of each token
    vocabulary: np.ndarray

    def bigrams(self, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(sorted distinct keys, the key index, context word index and word index of each token)."""
        context = np.empty_like(self.word)
        context[1:] = self.word[:-1]
        context[np.concatenate([[0], np.cumsum(self.size)[:-1]]).astype(np.int64)] = np.searchsorted(self.vocabulary, _keys(np.array([BOS]), bits))[0]
        key, at = np.unique(_keys(bigram_hashes(self.vocabulary[context], self.vocabulary[self.word]), bits), return_inverse=True)
        return key, at, context, self.word


def _segments(bits: int, tokens: int):
    def flush(parts, seg):
        ids, held, sizes, hashes = zip(*parts, strict=True)
        h = np.concatenate(hashes)
        vocabulary, word = np.unique(np.concatenate([_keys(h, bits), _keys(np.array([BOS]), bits)]), return_inverse=True)
        s = Segment(np.concatenate(sizes), word[:-1], vocabulary)
        held = np.concatenate(held)
        train = np.repeat(~held, s.size)
        key, at, _, _ = s.bigrams(bits)
        rows = []
        for kind, keys, count in (("w", vocabulary, np.bincount(s.word[train], minlength=len(vocabulary))), ("g", key, np.bincount(at[train], minlength=len(key)))):
            bucket = (keys >> U(LOW)).astype(np.int64)
            cut = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1], [True]]))
            for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                rows.append((kind, seg, int(bucket[a]), None, None, _packed(keys[a:b]), count[a:b].astype("<u4").tobytes()))
        end = 0
        for i, x, n in zip(np.concatenate(ids).tolist(), held.tolist(), s.size.tolist(), strict=True):
            rows.append(("d", seg, None, i[0], x, zlib.compress(s.word[end : end + n].astype("<u4").tobytes(), 1), None))
            end += n
        for a in range(0, len(rows), 4096):
            yield from _table(rows[a : a + 4096]).to_batches()

    def run(batches):
        seg, parts, total = TaskContext.get().partitionId() << 24, [], 0
        for batch in batches:
            for part in text_slices(batch):
                row, h, _ = hashed_words(part.column("text"))
                size = np.bincount(row, minlength=part.num_rows)
                h = np.insert(h, np.cumsum(size), END)
                ids = np.empty((part.num_rows, 1), object)
                ids[:, 0] = part.column("id").to_pylist()
                parts.append((ids, part.column("held").to_numpy(zero_copy_only=False).astype(bool), size + 1, h))
                total += len(h)
                if total >= tokens:
                    yield from flush(parts, seg)
                    seg, parts, total = seg + 1, [], 0
        if parts:
            yield from flush(parts, seg)

    return run


def _count(kind: str, top: int):
    """Totals of one bucket: its part of the table, the answers by segment, and how many keys occur r times (r <= top)."""

    def run(table: pa.Table) -> pa.Table:
        bucket = table["bucket"][0].as_py()
        segs, raw, counts = table["seg"].to_pylist(), table["a"].to_pylist(), table["b"].to_pylist()
        order = sorted(range(len(segs)), key=lambda i: segs[i])
        keys = [_unpacked(raw[i], bucket) for i in order]
        key, first, at = np.unique(np.concatenate(keys), return_index=True, return_inverse=True)
        total = np.bincount(at, np.concatenate([np.frombuffer(counts[i], "<u4") for i in order]), len(key)).astype(np.int64)
        seen = total > 0
        owner = np.zeros(len(at), bool)
        owner[first] = True
        rows = [("model", None, bucket, None, None, _packed(key[seen]), total[seen].astype("<u4").tobytes())]
        end = 0
        for i, k in zip(order, keys, strict=True):
            got = total[at[end : end + len(k)]].astype("<u4") | np.where(owner[end : end + len(k)], OWNED, np.uint32(0))
            rows.append((f"{kind}-answer", segs[i], bucket, None, None, got.astype("<u4").tobytes(), None))
            end += len(k)
        hist = np.bincount(np.minimum(total[seen], top + 2), minlength=top + 3).astype("<i8")
        rows.append(("stat", None, bucket, None, None, hist.tobytes(), np.array([total.sum(), seen.sum()], "<i8").tobytes()))
        return _table(rows)

    return run


def discounts(n: list[int], k: int) -> list[float]:
    """Factor for a count of r = 0..k (from k + 1 on it is 1) by Good-Turing over n[r], the number of things seen r times. Where
    that gives no factor in (0, 1], because a count of counts is empty or doesn't fall, half a count is taken from each instead."""
    n = [*n, *[0] * max(0, k + 2 - len(n))]
    half = [1.0] + [(r - 0.5) / r for r in range(1, k + 1)]
    if any(n[r] == 0 for r in range(1, k + 2)):
        return half
    common = (k + 1) * n[k + 1] / n[1]
    if common >= 1:
        return half
    d = [1.0] + [((r + 1) * n[r + 1] / n[r] / r - common) / (1 - common) for r in range(1, k + 1)]
    return d if all(0 < x <= 1 for x in d) else half


@dataclass
class Totals:
    tokens: int
    words: int
    documents: int
    d1: np.ndarray
    d2: np.ndarray
    mass: float  # of known words; the rest is the unknown word's

    def unigram(self, c: np.ndarray) -> np.ndarray:
        """Probability of words with these counts; 0 is the unknown word."""
        if not self.tokens:
            return np.ones(len(c))
        p = self.d1[np.minimum(c, len(self.d1) - 1)] * c / self.tokens
        return np.where(c > 0, p, 1 - self.mass)

    def share(self, c2: np.ndarray, c1: np.ndarray) -> np.ndarray:
        """Discounted share of bigrams with counts c2 in contexts with counts c1."""
        return self.d2[np.minimum(c2, len(self.d2) - 1)] * c2 / np.maximum(c1, 1)


def _totals(stats: DataFrame, top: int) -> tuple[np.ndarray, int, int]:
    """Sums of the buckets' statistics: a row a bucket, added up in the cluster."""

    def add(table: pa.Table) -> pa.Table:
        h = sum((np.frombuffer(x, "<i8") for x in table["a"].to_pylist()), np.zeros(top + 3, np.int64))
        t = sum((np.frombuffer(x, "<i8") for x in table["b"].to_pylist()), np.zeros(2, np.int64))
        return pa.table({"h": [h.tolist()], "t": [t.tolist()]}, pa.schema([("h", pa.list_(pa.int64())), ("t", pa.list_(pa.int64()))]))

    rows = stats.groupBy((F.col("bucket") % 64).alias("g")).applyInArrow(add, "h array<long>, t array<long>").collect()
    h, t = np.zeros(top + 3, np.int64), np.zeros(2, np.int64)
    for r in rows:
        h, t = h + np.array(r.h), t + np.array(r.t)
    return h, int(t[0]), int(t[1])


def _segment_of(table: pa.Table):
    """The parts of one segment: its documents' rows and word indexes, and the answers in the order of its keys."""
    kinds, buckets, a, b = (table[c].to_pylist() for c in ("kind", "bucket", "a", "b"))
    at = [i for i, k in enumerate(kinds) if k == "d"]

    def answer(kind, col, dtype):
        parts = sorted((buckets[i], i) for i, k in enumerate(kinds) if k == kind)
        return np.concatenate([np.frombuffer(col[i], dtype) for _, i in parts]) if parts else np.zeros(0, dtype)

    return at, a, b, kinds, buckets, answer


def _bigrams_of(at, a, kinds, buckets, bits):
    """Segment and bigrams, made again from what was written down."""
    parts = sorted((buckets[i], i) for i, k in enumerate(kinds) if k == "w")
    vocabulary = np.concatenate([_unpacked(a[i], bucket) for bucket, i in parts])
    word = [np.frombuffer(zlib.decompress(a[i]), "<u4").astype(np.int64) for i in at]
    s = Segment(np.array([len(w) for w in word], np.int64), np.concatenate(word), vocabulary)
    return s, s.bigrams(bits)


def scores(docs: DataFrame, held_out: Column, k: int = 5, id_col: str = "doc_id", text_col: str = "text", segment_tokens: int = SEGMENT_TOKENS, bucket_bits: int | None = None) -> DataFrame:
    """A row per row of docs: id, held_out, n_tokens, n_known, train_tokens, base_score, score; the model learns from rows that
    aren't held out. Null texts are empty and have their end only; rows with null or repeated ids are documents of their own.

    Probabilities of a context's known words and of the unknown word sum to 1. A context whose continuations are all too
    frequent to be discounted gives up one count; one never seen backs off with weight 1. Without training rows every word is unknown.
    """
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(held_out, F.lit(False)).alias("held"), F.col(text_col).alias("text"))
    bits = bucket_bits or min(16, max(8, math.ceil(math.log2(max(1, plan_bytes(docs)) / (8 << 20)))))
    table = staged(texts.mapInArrow(_segments(bits, segment_tokens), ROW), "segments", ["kind"])
    seg = table.select(*NAMES)
    of = lambda *kinds: seg.filter(F.col("kind").isin(*kinds))
    words = staged(of("w").groupBy("bucket").applyInArrow(_count("w", k), ROW), "words", ["kind"]).select(*NAMES)
    # in waves, so that only a part of the keys is being dealt at a time
    grams = None
    for wave in range(WAVES):
        some = of("g").filter(F.col("bucket") % WAVES == wave).groupBy("bucket").applyInArrow(_count("g", k), ROW)
        some = staged(some, "bigrams", ["kind"]).select(*NAMES)
        grams = some if grams is None else grams.unionAll(some)
    released(table, below="kind=g")
    n1, tokens, known = _totals(words.filter("kind = 'stat'"), k)
    n2, _, _ = _totals(grams.filter("kind = 'stat'"), k)
    d1, d2 = (np.array([*discounts(n.tolist(), k), 1.0]) for n in (n1, n2))
    taken = sum((1 - d1[r]) * r * int(n1[r]) for r in range(1, k + 1))
    documents = texts.filter("not held").count()
    t = Totals(tokens, known, documents, d1, d2, 1 - taken / tokens if tokens else 0.0)

    def counts(s: Segment, answer, a):
        w = answer("w-answer", a, "<u4") & ~OWNED
        context = w.astype(np.int64)
        context[np.searchsorted(s.vocabulary, _keys(np.array([BOS]), bits))[0]] = t.documents
        return w.astype(np.int64), context

    def sums(table: pa.Table) -> pa.Table:
        at, a, b, kinds, buckets, answer = _segment_of(table)
        s, (key, gram, context, word) = _bigrams_of(at, a, kinds, buckets, bits)
        w, c1 = counts(s, answer, a)
        got = answer("g-answer", a, "<u4")
        first = np.zeros(len(key), np.int64)
        first[gram] = np.arange(len(gram))  # any token of each bigram
        c2 = (got & ~OWNED).astype(np.int64)
        mine = ((got & OWNED) > 0) & (c2 > 0)
        x, y = context[first[mine]], word[first[mine]]
        p = np.bincount(x, t.share(c2[mine], c1[x]), len(s.vocabulary))
        u = np.bincount(x, t.unigram(w[y]), len(s.vocabulary))
        bucket = (s.vocabulary >> U(LOW)).astype(np.int64)
        cut = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1], [True]]))
        seg = table["seg"][0].as_py()
        return _table([("sum", seg, int(bucket[i]), None, None, np.concatenate([p[i:j], u[i:j]]).tobytes(), _packed(s.vocabulary[i:j])) for i, j in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)])

    def weights(table: pa.Table) -> pa.Table:
        bucket, segs = table["bucket"][0].as_py(), table["seg"].to_pylist()
        raw, keys = table["a"].to_pylist(), [_unpacked(x, table["bucket"][0].as_py()) for x in table["b"].to_pylist()]
        key, at = np.unique(np.concatenate(keys), return_inverse=True)
        p, u = np.zeros(len(key)), np.zeros(len(key))
        ends = np.concatenate([[0], np.cumsum([len(x) for x in keys])])
        for i, x in enumerate(raw):
            v = np.frombuffer(x, np.float64)
            here = at[ends[i] : ends[i + 1]]
            p[here] += v[: len(v) // 2]
            u[here] += v[len(v) // 2 :]
        return _table([("sum-answer", segs[i], bucket, None, None, p[at[ends[i] : ends[i + 1]]].tobytes(), u[at[ends[i] : ends[i + 1]]].tobytes()) for i in range(len(segs))])

    answers = words.filter("kind = 'w-answer'").unionAll(grams.filter("kind = 'g-answer'"))
    part = staged(of("d", "w").unionAll(answers).groupBy("seg").applyInArrow(sums, ROW), "sums")
    back = staged(part.groupBy("bucket").applyInArrow(weights, ROW), "weights")
    released(part)

    def told(table: pa.Table) -> pa.Table:
        at, a, b, kinds, buckets, answer = _segment_of(table)
        s, (key, gram, context, word) = _bigrams_of(at, a, kinds, buckets, bits)
        w, c1 = counts(s, answer, a)
        c2 = (answer("g-answer", a, "<u4") & ~OWNED).astype(np.int64)[gram]
        p, u = answer("sum-answer", a, np.float64), answer("sum-answer", b, np.float64)
        keep = np.where((c1 > 0) & (1 - p < 1e-9), c1 / (c1 + 1), 1.0)  # no discount left: the context gives up one count
        back = np.where(c1 > 0, (1 - keep * p) / np.maximum(1 - u, 1e-300), 1.0)
        one = t.unigram(w)
        seen = c2 > 0
        with np.errstate(divide="ignore"):
            token = np.where(seen, np.log10(np.where(seen, keep[context] * t.share(c2, c1[context]), 1.0)), np.log10(back[context]) + np.log10(one[word]))
            base = np.log10((w + 0.5) / (t.tokens + 0.5 * (t.words + 1)))[word]
        doc = np.repeat(np.arange(len(s.size)), s.size)
        add = lambda x: np.bincount(doc, x, len(s.size))
        ids, held = table["id"].to_pylist(), table["held"].to_pylist()
        return pa.table(
            [pa.array([ids[i] for i in at], pa.int64()), pa.array([held[i] for i in at]), pa.array(s.size), pa.array(add((w[word] > 0).astype(float)).astype(np.int64)), pa.array(np.full(len(at), t.tokens)), pa.array(add(base)), pa.array(add(token))],
            ["id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
        )

    every = of("d", "w").unionAll(answers).unionAll(back)
    return every.groupBy("seg").applyInArrow(told, "id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 1
    return scores(docs, held_out).withColumnRenamed("id", "doc_id")
