"""Line dedup by an exact set-similarity join.

A line's set holds its distinct words (lower-case A-Z, ASCII white space between them). Lines whose sets have a Jaccard
similarity of `percent` / 100 or more are alike; of these the first in (doc id, file, row, line number) stays and the later ones go.

Equal sets are one node, whose first line stands for it. Words are ordered by rarity: by their occurrences as a count-min sketch
of fixed size tells them, then by hash. Any total order makes prefix filtering exact, so the sketch's errors cost time only; it
never tells too few, so a word it counts once has no partner. A node posts the rest of its rarest words (prefix filter) with
its size, the word's place and a parity sketch. Postings are dealt by word into buckets, packed, and a bucket's pairs are made and
tested in blocks: the sizes must allow a match (length filter), and so must the words left after both places (positional filter)
and the sketches. What passes is verified on whole sets.

A node goes as soon as one earlier node is alike. So a bucket tells each node's nearest partners, where long posting lists are only
looked at next to the node and at their first one (long in pairs that sizes and places allow), and the nearest of all are verified before the others. Nodes that this doesn't
remove, and that had more partners than were told, then meet all of them; a long list is then cut into a grid of squares, each a
group of its own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm.common import SLICE_BYTES, addressed, free, from_buffers, hashed_words, mix64, packed, released, small, staged, text_buffers, text_slices, trim, trimmed, unpacked

U = np.uint64
COUNT_BITS = 22  # cells of a row of the count-min sketch
CELL_BITS = 20  # cells by which posting lists are counted
WORD = 5  # bytes of a posted word's hash
POSTINGS = 250_000  # of a bucket, on average
LONG = 20_000_000  # pairs of a posting list that the first round makes; of a longer one only a few each
FIRST = 3  # of a node's partners that are verified before the others
KEEP = 8  # partners of a node that a bucket tells in the first round
BESIDE = 16  # neighbours that it looks at in a longer one
SQUARE = 131_072  # entries at a side of a square
FLUSH = 300_000  # postings that are packed together
BLOCK = 200_000  # pairs tested at once
LOOKED_UP = 2_000_000  # lines to verify up to which their numbers are broadcast


def line_words(text: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Lines of texts, split at \\n: row of each line, its number in the row from 0, and line and hash of each word."""
    off, data = text_buffers(text)
    breaks = np.flatnonzero(data == 10)
    upto = np.searchsorted(breaks, off)
    count = 1 + np.diff(upto)
    owner = np.repeat(np.arange(len(count)), count)
    number = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
    row, h, start = hashed_words(text)
    return owner, number, row + np.searchsorted(breaks, start), h


def _ordered(line: np.ndarray, rank: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Order by (line, rank, h), ranks being below 256. Nearly all of it is told by one number."""
    if len(line) and line.max() >= 1 << 23:
        return np.lexsort((h, rank, line))
    key = line << 40 | rank.astype(np.int64) << 32 | (h >> U(32)).astype(np.int64)
    order = np.argsort(key)
    key, by = key[order], h[order]
    same = key[1:] == key[:-1]
    return np.lexsort((h, rank, line)) if (by[1:] != by[:-1])[same].any() else order


def line_sets(text: pa.Array, level: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(owner and number of each line; line, rank and hash of its distinct words, in the order of these)."""
    owner, number, line, h = line_words(text)
    rank = np.zeros(len(h), np.uint8)
    if level is not None:
        first, second = _cells(h)
        rank = np.minimum(level[first], level[second])
    order = _ordered(line, rank, h)
    line, rank, h = line[order], rank[order], h[order]
    new = np.ones(len(line), bool)
    new[1:] = (line[1:] != line[:-1]) | (h[1:] != h[:-1])
    return owner, number, line[new], rank[new], h[new]


# -- rarity


def _cells(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = mix64(h)
    return (x >> U(64 - COUNT_BITS)).astype(np.int64), ((x >> U(8)) & U((1 << COUNT_BITS) - 1)).astype(np.int64) + (1 << COUNT_BITS)


RANGES = 64  # parts of the sketch, each added up in one task


def _levels(n: np.ndarray) -> np.ndarray:
    """Counts as levels, 8 for a doubling; 0 stands for nothing and 1 for a single occurrence."""
    return np.where(n > 0, np.minimum(1 + np.floor(8 * np.log2(np.maximum(n, 1))), 255), 0).astype(np.uint8)


def word_levels(docs: DataFrame, text_col: str) -> np.ndarray:
    """The count-min sketch of all words' occurrences over all docs, as levels: 2 * 2**COUNT_BITS bytes whatever the input."""
    width = (2 << COUNT_BITS) // RANGES

    def count(batches):
        total = np.zeros(2 << COUNT_BITS, np.uint32)
        for batch in batches:
            for part in text_slices(batch):
                for cell in _cells(hashed_words(part.column("text"))[1]):
                    np.add.at(total, cell, np.uint32(1))
        out = []
        for k in range(RANGES):
            mine = total[k * width : (k + 1) * width]
            full = np.flatnonzero(mine)
            if len(full):
                out.append((k, packed(np.diff(full, prepend=0)), packed(mine[full])))
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], t) for i, t in enumerate((pa.int32(), pa.binary(), pa.binary()))], ["k", "cells", "n"])

    def add(table: pa.Table) -> pa.Table:
        total = np.zeros(width, np.int64)
        for cells, n in zip(table["cells"].to_pylist(), table["n"].to_pylist(), strict=True):
            total[np.cumsum(unpacked(cells))] += unpacked(n)
        return pa.table({"k": table["k"][:1], "levels": pa.array([_levels(total).tobytes()], pa.binary())})

    told = docs.select(F.col(text_col).alias("text")).mapInArrow(trimmed(count), "k int, cells binary, n binary").groupBy("k").applyInArrow(add, "k int, levels binary").toArrow()
    out = np.zeros(2 << COUNT_BITS, np.uint8)
    for k, raw in zip(told["k"].to_pylist(), told["levels"].to_pylist(), strict=True):
        out[k * width : (k + 1) * width] = np.frombuffer(raw, np.uint8)
    return out


# -- lines and their sets


def _binary(count: np.ndarray, body: np.ndarray) -> pa.Array:
    """Binary values of `count` bytes each from consecutive bytes."""
    off = np.concatenate([[0], np.cumsum(count)]).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(count), [None, pa.py_buffer(off.tobytes()), pa.py_buffer(np.ascontiguousarray(body).tobytes())])


def _sets(percent: int, least: int, levels):
    """Per line with `least` words or more: its address, digest (hi, lo), size, parity sketch (x, y), and what it posts."""

    def run(batches):
        level = levels.value
        for batch in batches:
            for part in text_slices(batch):
                owner, number, line, rank, h = line_sets(part.column("text"), level)
                n = len(owner)
                size = np.bincount(line, minlength=n)
                at = np.concatenate([[0], np.cumsum(size)])
                c = np.concatenate([np.zeros(1, U), np.cumsum(mix64(h ^ U(0xA0761D6478BD642F)), dtype=U)])
                d = np.concatenate([np.zeros(1, U), np.cumsum(mix64(h + U(0xE7037ED1A0B428DB)), dtype=U)])
                hi, lo = c[at[1:]] - c[at[:-1]], d[at[1:]] - d[at[:-1]]
                single = np.bincount(line, rank == 1, n).astype(np.int64)  # words without a partner, which come first
                post = np.maximum(size - -(-size * percent // 100) + 1 - single, 0)
                post[size * (100 - percent) < percent] = 0  # too few words for any set but an equal one
                use = size >= max(1, least)
                post[~use] = 0
                item = np.repeat(at[:-1] + single - np.concatenate([[0], np.cumsum(post)[:-1]]), post) + np.arange(post.sum())
                body = (mix64(h[item]) >> U(64 - 8 * WORD)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :WORD]
                pick = pa.array(owner[use])
                bit, full = U(1) << (h & U(63)), size > 0
                sketch = np.zeros((2, n), U)
                for k in (0, 1):
                    if len(h):
                        sketch[k, full] = np.bitwise_xor.reduceat(np.where((h >> U(6)) & U(1) == k, bit, U(0)), at[:-1][full])
                sketch = sketch[:, use].view(np.int64)
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("id").take(pick), part.column("file").take(pick), part.column("row").take(pick), pa.array(number[use].astype(np.int32)), pa.array(hi[use].view(np.int64)), pa.array(lo[use].view(np.int64)),
                        pa.array(size[use].astype(np.int32)), pa.array(sketch[0]), pa.array(sketch[1]), pa.array(single[use].astype(np.int32)), _binary(post[use] * WORD, body),
                    ],
                    ["id", "file", "row", "number", "hi", "lo", "n", "x", "y", "skip", "post"],
                )

    return run


def _words(batches):
    """The word hashes, as bytes, of the given lines of texts; other lines aren't looked at."""
    for batch in batches:
        for part in text_slices(batch):
            off, data = text_buffers(part.column("text"))
            breaks = np.flatnonzero(data == 10)
            begin = np.sort(np.concatenate([off[:-1], breaks + 1]), kind="stable")
            stop = np.concatenate([begin[1:], [len(data)]])
            wanted = part.column("numbers")
            k = pc.list_value_length(wanted).to_numpy(zero_copy_only=False).astype(np.int64)
            row = np.repeat(np.arange(part.num_rows), k)
            line = row + np.searchsorted(breaks, off[:-1])[row] + wanted.flatten().to_numpy(zero_copy_only=False)
            nodes = part.column("nodes").flatten()
            size = stop[line] - begin[line]
            ends = np.cumsum(size)
            a = 0
            while a < len(line):  # some lines at a time
                before = ends[a - 1] if a else 0
                b = max(a + 1, int(np.searchsorted(ends, before + SLICE_BYTES, "right")))
                n = size[a:b]
                at = np.repeat(begin[line[a:b]] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                owner, h, _ = hashed_words(from_buffers(np.concatenate([[0], np.cumsum(n)]), data[at]))
                order = _ordered(owner, np.zeros(len(h), np.uint8), h)
                owner, h = owner[order], h[order]
                new = np.ones(len(h), bool)
                new[1:] = (owner[1:] != owner[:-1]) | (h[1:] != h[:-1])
                yield pa.RecordBatch.from_arrays([nodes.slice(a, b - a), _binary(np.bincount(owner[new], minlength=b - a) * 8, h[new])], ["node", "words"])
                a = b


# -- postings


POSTED = "bucket int, p int, q int, word binary, node binary, n binary, pos binary, x binary, y binary, probe boolean"


def _flat(batch: pa.RecordBatch):
    """(entry's row, word, place) of all postings of a batch of nodes."""
    post = batch.column("post")
    off = np.frombuffer(post.buffers()[1], np.int32)[post.offset : post.offset + len(post) + 1].astype(np.int64)
    raw = np.frombuffer(post.buffers()[2], np.uint8)[off[0] : off[-1]] if off[-1] > off[0] else np.zeros(0, np.uint8)
    body = np.zeros((len(raw) // WORD, 8), np.uint8)
    body[:, :WORD] = raw.reshape(-1, WORD)
    count = np.diff(off) // WORD
    row = np.repeat(np.arange(len(count)), count)
    start = np.concatenate([[0], np.cumsum(count)[:-1]])
    pos = np.arange(len(row)) - start[row] + batch.column("skip").to_numpy().astype(np.int64)[row]
    return row, body.view("<i8").ravel(), pos


def _cell(word: np.ndarray) -> np.ndarray:
    return word >> (8 * WORD - CELL_BITS)


def list_sizes(nodes: DataFrame) -> np.ndarray:
    """Postings by cell of the word: a fixed number of cells whatever the input."""
    width = (1 << CELL_BITS) // RANGES

    def count(batches):
        total = np.zeros(1 << CELL_BITS, np.int64)
        for batch in batches:
            np.add.at(total, _cell(_flat(batch)[1]), 1)
        parts = [(k, packed(total[k * width : (k + 1) * width])) for k in range(RANGES)]
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in parts], t) for i, t in enumerate((pa.int32(), pa.binary()))], ["k", "n"])

    def add(table: pa.Table) -> pa.Table:
        return pa.table({"k": table["k"][:1], "n": pa.array([packed(sum(unpacked(x) for x in table["n"].to_pylist()))], pa.binary())})

    told = nodes.select("post", "skip").mapInArrow(trimmed(count), "k int, n binary").groupBy("k").applyInArrow(add, "k int, n binary").toArrow().sort_by("k")
    return np.concatenate([unpacked(x) for x in told["n"].to_pylist()]) if told.num_rows else np.zeros(1 << CELL_BITS, np.int64)


def _postings(sizes, buckets: int, square: int, side: str):
    """Packed postings by bucket and square: of the squares on the diagonal ("own", where the mark `probe` says that the list has more
    than one), of the grid's rows ("probe"), or of its columns where a probe has the word ("known")."""

    def run(batches):
        every, asked = sizes.value
        parts = np.maximum(1, -(-every // square))
        held, total = [], 0

        def flush():
            col = [np.concatenate(x) for x in zip(*held, strict=True)]
            group, word = col[0], col[1]
            order = np.lexsort((word, group))
            col = [x[order] for x in col]
            cut = np.flatnonzero(np.concatenate([[True], col[0][1:] != col[0][:-1], [True]]))
            rows = []
            for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                g = int(col[0][a])
                rows.append((g >> 33, g >> 17 & 0xFFFF, g >> 1 & 0xFFFF, packed(np.diff(col[1][a:b], prepend=0)), *(packed(x[a:b]) for x in col[2:5]), *(x[a:b].astype("<i8").tobytes() for x in col[5:7]), bool(g & 1)))
            kinds = [pa.int32()] * 3 + [pa.binary()] * 6 + [pa.bool_()]
            for a in range(0, len(rows), 256):
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows[a : a + 256]], t) for i, t in enumerate(kinds)], [x.split()[0] for x in POSTED.split(", ")])

        for batch in batches:
            row, word, pos = _flat(batch)
            node, n, x, y = (batch.column(c).to_numpy().astype(np.int64) for c in ("node", "n", "x", "y"))
            cell = _cell(word)
            if side == "known":
                keep = asked[cell] > 0
                row, word, pos, cell = row[keep], word[keep], pos[keep], cell[keep]
            bucket = word * buckets >> (8 * WORD)
            m = np.minimum(parts[cell], 0xFFFF)
            own = (mix64(node.view(U))[row] % m.astype(U)).astype(np.int64)
            i = np.arange(len(row))
            if side != "own":
                i = np.repeat(i, m)
                other = np.arange(len(i)) - np.repeat(np.cumsum(m) - m, m)
            p, q = {"own": (own, own), "probe": (own[i], None), "known": (None, own[i])}[side]
            group = bucket[i] << 33 | (other if p is None else p) << 17 | (other if q is None else q) << 1 | (m > 1 if side == "own" else side == "probe")
            held.append((group, word[i], node[row[i]], n[row[i]], pos[i], x[row[i]], y[row[i]]))
            total += len(i)
            if total >= FLUSH:
                yield from flush()
                held, total = [], 0
        if total:
            yield from flush()

    return run


def _entries(table: pa.Table):
    """Sorted by word, size and node: word, node, n, pos, the sketch's halves, and whether an entry is a probe."""
    cols = [[] for _ in range(7)]
    for word, node, n, pos, x, y, is_probe in zip(*(table[c].to_pylist() for c in ("word", "node", "n", "pos", "x", "y", "probe")), strict=True):
        parts = np.cumsum(unpacked(word)), unpacked(node), unpacked(n), unpacked(pos), np.frombuffer(x, "<i8"), np.frombuffer(y, "<i8")
        for c, part in zip(cols, (*parts, np.full(len(parts[0]), is_probe)), strict=True):
            c.append(part)
    word, node, n, *rest = map(np.concatenate, cols)
    order = np.lexsort((node, n, word))
    return tuple(x[order] for x in (word, node, n, *rest))


def _test(percent: int, n, pos, x, y, i, j) -> tuple[np.ndarray, np.ndarray]:
    """Which pairs the positional and the sketch filter allow, and the sketches' distance. It's enough to allow a pair at its first
    common word, before which nothing is common."""
    both = n[i] + n[j]
    need = -(-both * percent // (100 + percent))
    left = np.minimum(n[i] - pos[i], n[j] - pos[j])
    apart = (np.bitwise_count((x[i] ^ x[j]).view(U)) + np.bitwise_count((y[i] ^ y[j]).view(U))).astype(np.int64)
    return (left >= need) & (apart * (100 + percent) <= both * (100 - percent)), apart


def _blocks(start: np.ndarray, count: np.ndarray):
    """(i, j) for j in start[i] .. start[i] + count[i] - 1, some at a time."""
    ends = np.cumsum(count)
    a = 0
    while a < len(count):
        before = int(ends[a - 1]) if a else 0
        b = max(a + 1, int(np.searchsorted(ends, before + BLOCK, "right")))
        k = count[a:b]
        if b == a + 1 and k[0] > BLOCK:
            for x in range(0, int(k[0]), BLOCK):
                j = start[a] + np.arange(x, min(x + BLOCK, int(k[0])))
                yield np.full(len(j), a), j
        elif k.sum():
            i = np.repeat(np.arange(a, b), k)
            yield i, np.repeat(start[a:b] - np.concatenate([[0], np.cumsum(k)[:-1]]), k) + np.arange(k.sum())
        a = b


def _first_round(percent: int, most: int, beside: int):
    """Per node of a square its KEEP best earlier partners there, and whether there are or may be more (told in every row; a is -1 where
    there is none)."""

    def run(table: pa.Table) -> pa.Table:
        word, node, n, pos, x, y, split = _entries(table)
        at = np.arange(len(word))
        new = np.concatenate([[True], word[1:] != word[:-1]]) if len(word) else np.zeros(0, bool)
        gid = np.cumsum(new) - 1
        key = gid << 32 | n
        last = np.searchsorted(key, gid << 32 | 100 * n // percent, "right")
        # of equal or larger partners none passes if the place is too far back
        last[n - pos < -(-2 * n * percent // (100 + percent))] = 0
        pairs = np.bincount(gid, np.maximum(last - at - 1, 0)) if len(word) else np.zeros(0)
        long = pairs[gid] > most
        last = np.where(long, np.minimum(last, at + 1 + beside), last)
        best: list[tuple] = []

        def keep(i, j):
            ok, apart = _test(percent, n, pos, x, y, i, j)
            i, j = i[ok], j[ok]
            best.append(_nearest(np.maximum(node[i], node[j]), np.minimum(node[i], node[j]), apart[ok], np.zeros(len(i), bool)))
            if sum(len(x[0]) for x in best) > max(BLOCK, 2 * len(best[0][0])):
                best[:] = [_nearest(*(np.concatenate(x) for x in zip(*best, strict=True)))]

        for i, j in _blocks(at + 1, np.maximum(last - at - 1, 0)):
            keep(i, j)
        if long.any():
            order = np.lexsort((node, gid))
            first = order[np.concatenate([[True], gid[order][1:] != gid[order][:-1]])]
            i = np.flatnonzero(long)
            j = first[gid[i]]
            fit = (i != j) & (100 * np.minimum(n[i], n[j]) >= percent * np.maximum(n[i], n[j]))
            keep(i[fit], j[fit])
        if long.any() or split.any():
            i = np.unique(node[long | split])  # may have more
            best.append((i, np.full(len(i), -1), np.full(len(i), 1 << 20), np.ones(len(i), bool)))
        cols = [np.concatenate(x) for x in zip(*best, strict=True)] if best else [np.zeros(0, np.int64)] * 3 + [np.zeros(0, bool)]
        b, a, apart, more = _nearest(*cols)
        trim()
        return pa.table([pa.array(b), pa.array(a), pa.array(apart), pa.array(more)], ["b", "a", "apart", "more"])

    return run


def _nearest(b, a, apart, more):
    """The KEEP nearest a of each b, each once; more: some row of b says so, or it had others."""
    order = np.lexsort((a, apart, b))
    b, a, apart, more = b[order], a[order], apart[order], more[order]
    once = np.ones(len(b), bool)
    once[1:] = (b[1:] != b[:-1]) | (a[1:] != a[:-1])
    cut = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]])) if len(b) else np.zeros(0, np.int64)
    size = np.diff(np.append(cut, len(b)))
    nth = np.cumsum(once) - np.repeat((np.cumsum(once) - once)[cut], size)
    if len(b):
        more = np.repeat(np.logical_or.reduceat(more | (nth > KEEP), cut), size)
    stay = once & (nth <= KEEP)
    return b[stay], a[stay], apart[stay], more[stay]


def _second_round(percent: int):
    """All pairs of a square whose later node is a probe."""

    def run(table: pa.Table) -> pa.Table:
        word, node, n, pos, x, y, probe = _entries(table)
        out = [[], [], []]
        asked, known = np.flatnonzero(probe), np.flatnonzero(~probe)
        if len(asked) and len(known):
            _, gid = np.unique(word, return_inverse=True)
            key = gid[known] << 32 | n[known]
            start = np.searchsorted(key, gid[asked] << 32 | -(-n[asked] * percent // 100), "left")
            stop = np.searchsorted(key, gid[asked] << 32 | 100 * n[asked] // percent, "right")
            for i, j in _blocks(start, np.maximum(stop - start, 0)):
                i, j = asked[i], known[j]
                earlier = node[j] < node[i]
                i, j = i[earlier], j[earlier]
                ok, apart = _test(percent, n, pos, x, y, i, j)
                for c, v in zip(out, (node[i[ok]], node[j[ok]], apart[ok]), strict=True):
                    c.append(v)
        b, a, apart = (np.concatenate(c) if c else np.zeros(0, np.int64) for c in out)
        if len(b):
            order = np.lexsort((a, b))
            a, b, apart = a[order], b[order], apart[order]
            new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
            a, b, apart = a[new], b[new], apart[new]
        return pa.table([pa.array(b), pa.array(a), pa.array(apart)], ["b", "a", "apart"])

    return run


def _alike(percent: int):
    @F.arrow_udf("boolean")
    def alike(x: pa.Array, y: pa.Array) -> pa.Array:
        out = np.zeros(len(x), bool)
        for k, (v, w) in enumerate(zip(x, y, strict=True)):
            v, w = np.frombuffer(v.as_buffer(), "<u8"), np.frombuffer(w.as_buffer(), "<u8")
            common = len(np.intersect1d(v, w, assume_unique=True))
            out[k] = 100 * common >= percent * (len(v) + len(w) - common)
        return pa.array(out)

    return alike


def mark(docs: DataFrame, file: str, row: str, percent: int = 80, least: int = 3, id_col: str = "doc_id", text_col: str = "text", long: int = LONG, beside: int = BESIDE, square: int = SQUARE) -> DataFrame:
    """Lines that go: (file, row, number), file and row being the address of a row of docs that these columns hold, and number the
    line's place from 0.

    A line goes if an earlier line is alike; earlier by (id, file, row, number), null ids last. Lines with fewer than `least`
    distinct words, and those without words, stay. Null texts have no lines with words. `long`, `beside` and `square` tell when
    work is split, and don't change the result.
    """
    spark = docs.sparkSession
    levels = spark.sparkContext.broadcast(word_levels(docs, text_col))
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(file).alias("file"), F.col(row).alias("row"), F.col(text_col).alias("text"))
    lines = staged(texts.mapInArrow(trimmed(_sets(percent, least, levels)), "id long, file long, row long, number int, hi long, lo long, n int, x long, y long, skip int, post binary"), "lines")
    # a set's first line, with what it posts
    place = F.struct(F.col("id").isNull().alias("none"), "id", "file", "row", "number", "n", "x", "y", "skip", "post")
    equal = lines.groupBy("hi", "lo").agg(F.min(place).alias("at"), F.count("*").alias("k")).select("hi", "lo", "k", "at.*")
    # nodes have numbers in that order: of id and line where ids are different and leave room, else by sorting
    told = texts.agg(F.min("id").alias("least"), F.max("id").alias("most"), F.count("*").alias("rows"), F.count("id").alias("ids")).head()
    far = lines.agg(F.max("number")).head()[0] or 0
    room = told.least is not None and (told.most - told.least).bit_length() + far.bit_length() <= 62 and told.ids == told.rows
    if room and not texts.groupBy("id").count().filter("count > 1").limit(1).count():
        numbered = equal.withColumn("node", F.shiftleft(F.col("id") - told.least, far.bit_length()).bitwiseOR(F.col("number").cast("long")))
    else:
        numbered = equal.orderBy("none", "id", "file", "row", "number").withColumn("node", F.monotonically_increasing_id())
    nodes = staged(numbered.select("node", "hi", "lo", "k", "file", "row", "number", "n", "x", "y", "skip", "post"), "nodes")
    posting = nodes.filter(F.octet_length("post") > 0).select("node", "n", "x", "y", "skip", "post")
    verified = _alike(percent)
    every = list_sizes(posting)
    buckets = max(1, int(-(-every.sum() // POSTINGS)))
    group = ["bucket", "p", "q"]

    def found(pairs: DataFrame) -> DataFrame:
        """Staged nodes b of candidate pairs (a before b) that are alike."""
        used = staged(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "used")
        of = nodes.select("node", "file", "row", "number").join(small(used), "node")
        by_doc = of.groupBy("file", "row").agg(F.collect_list("node").alias("nodes"), F.collect_list("number").alias("numbers"))
        by_doc = staged(by_doc, "by-doc")
        few = (by_doc.agg(F.sum(F.size("nodes"))).head()[0] or 0) <= LOOKED_UP
        asked = texts.select("file", "row", "text").join(F.broadcast(by_doc) if few else by_doc, ["file", "row"]).select("nodes", "numbers", "text")
        words = staged(asked.mapInArrow(trimmed(_words), "node long, words binary"), "words")
        side = lambda k: words.select(F.col("node").alias(k), F.col("words").alias(f"w{k}"))
        both = pairs.select("a", "b").join(side("b"), "b").join(side("a"), "a")
        out = staged(both.filter(verified("wa", "wb")).select(F.col("b").alias("node")).distinct(), "alike")
        released(used, words, by_doc)
        return out

    def tried(pairs: DataFrame) -> DataFrame:
        """Nodes b that are alike to a node of staged pairs (b, a, apart): the nearest ones first, the others only where none of these is."""
        near = F.explode(F.slice(F.array_sort(F.collect_set(F.struct("apart", "a"))), 1, FIRST))
        nearest = staged(pairs.groupBy("b").agg(near.alias("s")).select("b", "s.a"), "nearest")
        hit = found(nearest)
        rest = pairs.select("b", "a").distinct().join(nearest, ["b", "a"], "left_anti").join(hit.withColumnRenamed("node", "b"), "b", "left_anti")
        rest = staged(rest, "others")
        return hit.union(found(rest)) if rest.limit(1).count() else hit

    told = spark.sparkContext.broadcast((every, None))
    seen = posting.mapInArrow(trimmed(_postings(told, buckets, square, "own")), POSTED).groupBy(*group).applyInArrow(_first_round(percent, long, beside), "b long, a long, apart long, more boolean")
    seen = staged(seen, "seen")
    pairs = seen.filter("a >= 0").select("b", "a", "apart")
    gone = tried(pairs)
    open_ = staged(seen.filter("more").select(F.col("b").alias("node")).distinct().join(gone, "node", "left_anti"), "open")
    if open_.limit(1).count():  # what had more partners than were told meets all of them
        asking = staged(posting.join(small(open_), "node", "left_semi"), "asking")
        told = spark.sparkContext.broadcast((every, list_sizes(asking)))
        met = asking.mapInArrow(trimmed(_postings(told, buckets, square, "probe")), POSTED).unionAll(posting.mapInArrow(trimmed(_postings(told, buckets, square, "known")), POSTED))
        met = met.groupBy(*group).applyInArrow(_second_round(percent), "b long, a long, apart long")
        gone = gone.union(tried(staged(met.join(pairs.select("b", "a"), ["b", "a"], "left_anti"), "met")))
        released(asking)
    released(seen)
    gone = gone.distinct()
    # a node that goes loses all its lines; of the others every line but the first goes
    state = nodes.select("hi", "lo", "node", "k", F.col("file").alias("file1"), F.col("row").alias("row1"), F.col("number").alias("number1")).join(gone.withColumn("all", F.lit(True)), "node", "left").filter("k > 1 or all")
    state = staged(state.select("hi", "lo", "file1", "row1", "number1", F.coalesce("all", F.lit(False)).alias("all")), "state")
    released(nodes)
    out = lines.select("file", "row", "number", "hi", "lo").join(state.hint("shuffle_hash"), ["hi", "lo"])
    return out.filter("all or file != file1 or row != row1 or number != number1").select("file", "row", "number")


def _without():
    """Texts without the lines of the given numbers; null where there are none."""

    @F.arrow_udf("string")
    def without(text: pa.Array, bad: pa.Array) -> pa.Array:
        out = []
        for t, b in zip(text, bad, strict=True):
            if not b.is_valid or not t.is_valid:
                out.append(None)
                continue
            lines = t.as_py().split("\n")
            keep = np.ones(len(lines), bool)
            keep[b.values.to_numpy()] = False
            out.append("\n".join(x for x, k in zip(lines, keep.tolist(), strict=True) if k))
        return pa.array(out, pa.string())

    return without


def drop_lines(docs: DataFrame, percent: int = 80, least: int = 3, id_col: str = "doc_id", text_col: str = "text", count_col: str | None = "n_chars", **split) -> DataFrame:
    """docs without the lines that mark() names; `count_col`, where docs has it, becomes the length of a text that changed.

    `split` goes to mark(). All rows and columns stay; a text may become empty, a null text stays null. Other lines keep their order and their bytes.
    """
    rows, file, row = addressed(docs)
    bad = free("bad", rows.columns)
    gone = mark(rows, file, row, percent, least, id_col, text_col, **split)
    gone = staged(gone.groupBy("file", "row").agg(F.collect_list("number").alias(bad)), "bad").withColumnsRenamed({"file": f"{bad}_f", "row": f"{bad}_r"})
    met = rows.join(gone.hint("shuffle_hash"), (rows[file] == gone[f"{bad}_f"]) & (rows[row] == gone[f"{bad}_r"]), "left")
    new = free("new", met.columns)
    met = met.withColumn(new, _without()(F.when(F.col(bad).isNotNull(), F.col(text_col)), F.col(bad)))
    changed = F.col(bad).isNotNull()
    kept = {text_col: F.when(changed, F.col(new)).otherwise(F.col(text_col))}
    if count_col in docs.columns:
        kept[count_col] = F.when(changed, F.char_length(new).cast(docs.schema[count_col].dataType)).otherwise(F.col(count_col))
    return met.select(*(kept[c].alias(c) if c in kept else F.col(f"`{c}`") for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: its lines, those that went, and the digest of what stays."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    kept = drop_lines(docs.withColumn("before", F.size(F.split(F.coalesce("text", F.lit("")), "\n", -1)).cast("long")), least=1, count_col=None)
    return kept.select(
        "doc_id", F.col("before").alias("n_lines"), F.char_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_chars_kept"),
        F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"),
    )
