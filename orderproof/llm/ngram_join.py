"""Exact Jaccard join of word n-gram sets by parity sketches.

Every set is cut by hash into segments, and each segment keeps the XOR of its n-grams' 64-bit hashes. Sets that meet
the threshold differ in at most d n-grams, so of d+1 segments one has equal parities: that is the join key, per size band (a few more segments make up for empty ones).
The Hamming distance of whole-set sketches, which is never above the symmetric difference, then discards most pairs, and exact
sets decide the rest. Equal sets are one node from the start. First each node is compared with the smallest one it
shares a bucket with; later only members of different components are, so a group of near copies isn't expanded into all its pairs.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.llm.common import addressed, components, hashed_words, mix64, released, small, staged, text_slices, trimmed

SKETCH_WORDS = 16  # of 64 bits
WAVES = 4
U = np.uint64


def shingle_sets(text: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, 64-bit hash), sorted and distinct, of the word n-grams of each text; a text with fewer words has its whole
    sequence as one, a text without words none."""
    rows, h, _ = hashed_words(text)
    if not len(h):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    count = np.bincount(rows, minlength=len(text))
    first = np.concatenate([[0], np.cumsum(count)[:-1]])
    out_rows, out = [], []
    if len(h) >= n:
        x = np.zeros(len(h) - n + 1, np.uint64)
        for k in range(n):
            x = mix64(x * U(0x9E3779B97F4A7C15) + h[k : len(h) - n + 1 + k])
        whole = rows[: len(h) - n + 1] == rows[n - 1 :]
        out_rows.append(rows[: len(h) - n + 1][whole])
        out.append(x[whole])
    for short in range(1, n):  # texts of fewer than n words
        at = first[count == short]
        if len(at):
            x = np.full(len(at), U(short))
            for k in range(short):
                x = mix64(x * U(0x9E3779B97F4A7C15) + h[at + k])
            out_rows.append(rows[at])
            out.append(x)
    r, x = np.concatenate(out_rows), np.concatenate(out)
    order = np.lexsort((x, r))
    r, x = r[order], x[order]
    new = np.ones(len(r), bool)
    new[1:] = (r[1:] != r[:-1]) | (x[1:] != x[:-1])
    return r[new], x[new]


def bands(percent: int, most: int) -> np.ndarray:
    """First sizes of the bands, each 1.5 times the one before, beyond `most`."""
    out = [1]
    while out[-1] <= 100 * most // percent + 1:
        out.append(-(-out[-1] * 3 // 2))
    return np.array([*out, -(-out[-1] * 3 // 2)])


def join_keys(row: np.ndarray, h: np.ndarray, size: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, key, cut, need) for sorted sets. A set takes part in the group of its band (cut 0), and in the next one if a partner can lie
    there (1); 2 and 3 are second cuts for these. need: partners share at least so many keys of a set's cut."""
    start = bands(percent, int(size.max(initial=1)))
    band = np.searchsorted(start, size, "right") - 1
    at = np.concatenate([[0], np.cumsum(size)])
    both_row, both_group = [], []
    for up in (0, 1):
        takes = (size > 0) & ((100 * size // percent >= start[np.minimum(band + 1, len(start) - 1)]) if up else True)
        both_row.append(np.flatnonzero(takes))
        both_group.append(band[takes] + up)
    rows, group = np.concatenate(both_row), np.concatenate(both_group)
    cut = np.repeat([0, 1], [len(x) for x in both_row])
    apart = 2 * (start[group + 1] - 1) * (100 - percent) // (100 + percent)
    spare = (0.15 * (apart + 1) + 2 * np.sqrt(0.06 * (apart + 1))).astype(np.int64)
    parts = apart + 1 + spare

    def segments(rows, parts, tag, again):
        """Owner (index into rows) and key of each segment, and whether it holds anything."""
        n = size[rows]
        owner = np.repeat(np.arange(len(rows)), parts)
        base = np.concatenate([[0], np.cumsum(parts)[:-1]]).astype(np.int64)
        name = mix64(tag[owner] * U(0x2545F4914F6CDD1D) + (np.arange(len(owner)) - base[owner]).astype(U))
        seen = np.zeros(len(owner), bool)
        if len(owner):
            item = np.repeat(at[rows] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
            entry = np.repeat(np.arange(len(rows)), n)
            x = mix64(h[item] ^ U(0x5851F42D4C957F2D)) if again else h[item]
            slot = base[entry] + (((x >> U(32)) * parts[entry].astype(U)) >> U(32)).astype(np.int64)
            if again:
                order = np.argsort(slot, kind="stable")
                slot, x = slot[order], x[order]
            cut = np.flatnonzero(np.concatenate([[True], slot[1:] != slot[:-1]]))  # sorted hashes fill segments in order
            parity = np.bitwise_xor.reduceat(mix64(x + U(1)), cut)
            seen[slot[cut]] = True
            name[slot[cut]] = mix64(parity ^ name[slot[cut]])
        return owner, name, seen

    # Of the segments at least spare + 1 are equal. An empty one says nothing, so a set with more empty ones than `spare` also
    # takes part in a second cut, by another hash: two such sets may agree in empty segments only.
    owner, key, seen = segments(rows, parts, mix64(group.astype(U)), False)
    need = spare + 1 - np.bincount(owner[~seen], minlength=len(rows))
    bare = np.flatnonzero(need < 1)
    owner2, key2, _ = segments(rows[bare], apart[bare] + 1, mix64(group[bare].astype(U) + U(1 << 32)), True)
    one = owner[seen]
    return (
        np.concatenate([rows[one], rows[bare][owner2]]), np.concatenate([key[seen], key2]),
        np.concatenate([cut[one], cut[bare][owner2] + 2]), np.concatenate([np.maximum(need, 1)[one], np.ones(len(owner2), np.int64)]),
    )


def _sums(row: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    """Wrapping sum of x by sorted row."""
    c = np.concatenate([np.zeros(1, np.uint64), np.cumsum(x, dtype=np.uint64)])
    ends = np.searchsorted(row, np.arange(n + 1))
    return c[ends[1:]] - c[ends[:-1]]


def _lists(row: np.ndarray, x: np.ndarray, n: int) -> pa.Array:
    ends = np.searchsorted(row, np.arange(n + 1)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(x.view(np.int64) if x.dtype == U else x))


def _digests(row, h, n):
    return _sums(row, mix64(h ^ U(0xA0761D6478BD642F)), n).view(np.int64), _sums(row, mix64(h + U(0xE7037ED1A0B428DB)), n).view(np.int64)


def _describe(n: int, percent: int):
    def run(batches):
        uid = TaskContext.get().partitionId() << 33
        for batch in batches:
            for part in text_slices(batch):
                row, h = shingle_sets(part.column("text"), n)
                m = part.num_rows
                size = np.bincount(row, minlength=m)
                hi, lo = _digests(row, h, m)
                krow, key, cut, need = join_keys(row, h, size, percent)
                order = np.argsort(krow, kind="stable")
                told = (need << 2 | cut)[order]
                bits = np.bincount(row * (SKETCH_WORDS * 64) + (h % U(SKETCH_WORDS * 64)).astype(np.int64), minlength=m * SKETCH_WORDS * 64)
                sketch = np.packbits((bits & 1).astype(np.uint8)).view(np.int64)
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("id"), part.column("file"), part.column("row"), pa.array(np.arange(uid, uid + m)), pa.array(size), pa.array(hi), pa.array(lo), _lists(krow[order], key[order], m), _lists(krow[order], told.astype(np.int32), m),
                        pa.ListArray.from_arrays(pa.array(np.arange(0, m * SKETCH_WORDS + 1, SKETCH_WORDS, dtype=np.int32)), pa.array(sketch)),
                    ],
                    ["id", "file", "row", "uid", "n", "hi", "lo", "keys", "told", "sketch"],
                )
                uid += m

    return run


def _exact(n: int):
    def run(batches):
        for batch in batches:
            for part in text_slices(batch):
                row, h = shingle_sets(part.column("text"), n)
                hi, lo = _digests(row, h, part.num_rows)
                same = pa.array((hi == part.column("hi").to_numpy()) & (lo == part.column("lo").to_numpy()))
                out = pa.RecordBatch.from_arrays([part.column("node"), _lists(row, h, part.num_rows)], ["node", "grams"])
                yield out.filter(same)

    return run


def link(docs: DataFrame, n: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", address: tuple[str, str] | None = None) -> tuple[DataFrame, DataFrame]:
    """(members, edges): a row per row of docs with id, file and row (the columns of `address`, if given), n_shingles, component_id and group (a number of the component), and verified links (a, b) of node ids.

    Texts link where 100 * |A & B| >= percent * |A | B| over their n-gram sets; component_id is the smallest id reachable. Null ids
    are rows too, whose component is the smallest other id, or null. Texts without words link with nothing. Rows with the same id but
    other texts are documents of their own. Other columns aren't read.
    """
    file, row = map(F.col, address) if address else (F.lit(None), F.lit(None))
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), file.cast("long").alias("file"), row.cast("long").alias("row"))
    rows = staged(texts.mapInArrow(trimmed(_describe(n, percent)), "id long, file long, row long, uid long, n long, hi long, lo long, keys array<long>, told array<int>, sketch array<long>"), "sets")
    full = rows.filter("n > 0")
    same = full.groupBy("hi", "lo").agg(F.min("uid").alias("node"), F.min("id").alias("first"))
    same = staged(same, "same")
    nodes = full.select(F.col("uid").alias("node"), "keys", "told").join(small(same.select("node")), "node", "left_semi")
    parts = []
    for wave in range(WAVES):  # a part of the keys is dealt at a time
        keyed = nodes.select("node", F.inline(F.arrays_zip("keys", "told"))).select("node", F.col("keys").alias("key"), "told").filter(F.pmod("key", F.lit(WAVES)) == wave)
        several = keyed.groupBy("key").agg(F.count("*").alias("often")).filter("often > 1")
        parts.append(staged(keyed.join(several, "key").distinct(), "keys"))
    # Partners share `need` keys of a cut at least, so they share one beside the need - 1 most frequent of each: those go, and with them
    # what a common passage gives to very many texts. The order of keys is the same for all.
    rank = F.row_number().over(W.partitionBy("node", F.col("told").bitwiseAND(F.lit(3))).orderBy(F.desc("often"), "key"))
    left = staged(reduce(DataFrame.unionAll, parts).withColumn("rank", rank).filter(F.col("rank") >= F.shiftright("told", 2)).select("key", "node").distinct(), "rare")
    released(*parts)
    several = left.groupBy("key").agg(F.min("node").alias("low"), F.max("node").alias("high")).filter("low != high").select("key", "low")
    shared = staged(left.join(several, "key"), "shared")
    released(left)
    # one pair a node: most of a group is joined by these, and what isn't meets again below
    pairs = staged(shared.filter("node != low").groupBy(F.col("node").alias("b")).agg(F.min("low").alias("a")), "pairs")
    light = full.select(F.col("uid").alias("node"), "n", "sketch")

    def near() -> Column:
        apart = F.aggregate(F.zip_with("sa", "sb", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda t, x: t + x)
        return apart * (100 + percent) <= (F.col("na") + F.col("nb")) * (100 - percent)

    def verified(pairs: DataFrame) -> DataFrame:
        side = lambda k: light.select(F.col("node").alias(k), F.col("n").alias(f"n{k}"), F.col("sketch").alias(f"s{k}"))
        met = pairs.join(side("b"), "b").join(side("a"), "a")
        close = staged(met.filter(near()).select("a", "b", "na", "nb"), "close")
        used = close.select(F.explode(F.array("a", "b")).alias("node")).distinct()
        wanted = staged(same.join(used, "node"), "wanted")
        own = texts.join(small(wanted), F.col("id").eqNullSafe(F.col("first"))).select("node", "hi", "lo", "text")
        grams = own.mapInArrow(trimmed(_exact(n)), "node long, grams array<long>").dropDuplicates(["node"])
        grams = staged(grams, "grams")
        met = close.join(grams.select(F.col("node").alias("b"), F.col("grams").alias("gb")), "b").join(grams.select(F.col("node").alias("a"), F.col("grams").alias("ga")), "a")
        met = met.withColumn("common", F.size(F.array_intersect("ga", "gb")))
        links = staged(met.filter(100 * F.col("common") >= percent * (F.col("na") + F.col("nb") - F.col("common"))).select("a", "b"), "links")
        released(close, grams, wanted)
        return links

    edges = verified(pairs)
    known = components(edges)
    of = shared.join(known, "node", "left").select("key", "node", F.coalesce("component", "node").alias("c"))
    mixed = of.groupBy("key").agg(F.min("c").alias("least"), F.max("c").alias("most")).filter("least != most").select("key", "least")
    # of the pairs in a bucket only those go on that the sketches allow
    of = staged(of.join(mixed, "key").join(light, "node"), "mixed")
    of, other = (of.select("key", "least", F.col("node").alias(x), F.col("c").alias(f"c{x}"), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}")) for x in "ab")
    other = other.withColumnRenamed("key", "key2")
    met = of.filter("ca != least").join(other.drop("least"), (F.col("key") == F.col("key2")) & (F.col("ca") != F.col("cb")) & near())
    cross = met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    more = staged(cross.join(pairs, ["a", "b"], "left_anti"), "cross")
    if more.limit(1).count():
        edges = edges.union(verified(more))
        known = components(edges)
    names = same.join(known, "node", "left").select("hi", "lo", "node", "first", F.coalesce("component", "node").alias("c"))
    least = names.groupBy("c").agg(F.min("first").alias("component_id"))
    names = staged(names.join(least, "c").select("hi", "lo", "component_id", F.col("c").alias("group")), "names")
    alone = rows.filter("n = 0").select("id", "file", "row", F.col("n").alias("n_shingles"), F.col("id").alias("component_id"), F.col("uid").alias("group"))
    grouped = rows.filter("n > 0").join(names, ["hi", "lo"]).select("id", "file", "row", F.col("n").alias("n_shingles"), "component_id", "group")
    return grouped.unionAll(alone), edges


def first_of_each(docs: DataFrame, n: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay: of each group of near duplicates the one with the smallest id (one of them, where ids
    repeat). Texts without words stay."""
    rows, file, row = addressed(docs)
    members, _ = link(rows, n, percent, id_col, text_col, (file, row))
    members = staged(members.select("id", "file", "row", "n_shingles", "group"), "members")
    place = F.struct(F.col("id").isNull().alias("none"), "id", "file", "row")
    first = members.filter("n_shingles > 0").groupBy("group").agg(F.min(place).alias("first"))
    gone = members.filter("n_shingles > 0").join(first, "group").filter("file != first.file OR row != first.row").select(F.col("file").alias(file), F.col("row").alias(row))
    return rows.join(small(staged(gone, "gone")), [file, row], "left_anti").select(*(F.col(f"`{c}`") for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    members, _ = link(docs, n=4, percent=85)
    return members.select(F.col("id").alias("doc_id"), "n_shingles", "component_id")


ORACLE = r"""
WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
      ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' '))) END AS s FROM w),
g AS (SELECT doc_id, len(s) AS n, unnest(s) AS x FROM s),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k, any_value(a.n) AS na, any_value(b.n) AS nb FROM g a JOIN g b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM c WHERE 100 * k >= 85 * (na + nb - k)),
l AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (WITH RECURSIVE r(x, y) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.x, l.b FROM r JOIN l ON r.y = l.a) SELECT x, min(y) AS m FROM r GROUP BY x)
SELECT s.doc_id, len(s.s) AS n_shingles, r.m AS component_id FROM s JOIN r ON r.x = s.doc_id
"""
