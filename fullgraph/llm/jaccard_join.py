"""Exact n-gram Jaccard self-join with size-banded tiles and hashed bitmap signatures.

Two documents link when ``100 * |A and B| >= percent * |A or B|`` over their sets
of word shingles.  The result names each document's component.

1.  *Sets.*  A first pass over whole texts gives each document its set size and
    a 128-bit key of the set, and counts all shingles of the corpus into a table
    of ``COUNTERS`` hashed counters (summed on the executors; the table has a
    fixed size).  Documents with one key are one class from here on.
2.  *Signatures.*  A second pass gives each class a parity bitmap, whose width
    follows the set size, and the prefix of its shingles in the order (count
    table, hash).  Any fixed order is exact: two sets that link share a shingle
    of their prefixes.  Counting first moves shingles that much of the corpus
    shares out of the prefixes.
3.  *Star round.*  Within a prefix shingle and size band every class is paired
    with the smallest one only, so a group of m gives m pairs.  Pairs pass size,
    then bit counts (``|A and B| <= (|A| + |B| - bits that differ) / 2``), then
    the exact intersection of sorted arrays.  Links make components.
4.  *Tile round.*  Pairs that share a prefix shingle but are in different
    components are all checked.  Rows of the largest component and the other rows
    of a shingle are dealt into blocks; a tile is a pair of blocks of which one
    holds other rows, so pairs inside the large component are never formed.
    Bitmaps are compared in the tile; only pairs that pass them leave it.  In the
    first passes a tile lets each component's ``BEST`` closest pairs leave, and
    what they link is merged; the last pass lets all that are still apart leave,
    so the components are exact while a group of near copies gives few pairs.

Hashes are 64 bit; a collision of two shingles within one pair of documents is
the only way to a wrong count.

Defined results: no words or null text is an empty set, linked with nothing;
rows that repeat a ``doc_id`` are one node; a null ``doc_id`` has a null
component; extra columns pass unread; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import math
from collections import OrderedDict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import fresh, ship, slices, spread, stored
from .components import connected
from .shingles import shingle_sets

COUNTERS = 1 << 20
PARTS = 64
FAN_IN = 64
TILE = 1024
BEST = (3, None)


def least_overlap(n: int, m: int, percent: int) -> int:
    """The smallest intersection with which sets of n and m shingles link."""
    return -(-percent * (n + m) // (100 + percent))


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1 if n else 0


def band(n: np.ndarray | int, percent: int):
    """Sizes that can link are in the same or the next band."""
    return np.floor(np.log(np.maximum(n, 1)) / -math.log(percent / 100 - 0.001)).astype(np.int64)


def _width(n: int) -> int:
    # with one to two bits per shingle few differences fall on one bit, so the bound is close to the true overlap
    return 1 << max(6, n.bit_length())


def parity_bitmap(hashes: np.ndarray) -> bytes:
    w = _width(len(hashes))
    at = ((hashes >> np.uint64(20)) & np.uint64(w - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=w) & 1).astype(np.uint8), bitorder="little").tobytes()


def fold(bits: np.ndarray, words: int) -> np.ndarray:
    """A wider parity bitmap (rows of 64-bit words) at a smaller width."""
    while bits.shape[-1] > words:
        half = bits.shape[-1] // 2
        bits = bits[..., :half] ^ bits[..., half:]
    return bits


# ---------------------------------------------------------------- passes over the texts


def _first_pass(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        count = np.zeros(COUNTERS, dtype=np.int64)
        for batch in slices(batches, "text", 1 << 20):
            sets = shingle_sets([t or "" for t in batch.column(1).to_pylist()], k)
            keys = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
            if any(map(len, sets)):
                count += np.bincount((np.concatenate(sets) & np.uint64(COUNTERS - 1)).astype(np.int64), minlength=COUNTERS)
            n = len(sets)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys, pa.binary()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())],
                names=["doc_id", "n", "set_key", "part", "lane", "counts"],
            )
        if count.any():
            lane = TaskContext.get().partitionId()
            blobs = [c.astype("<u4").tobytes() for c in np.split(count, PARTS)]
            yield pa.RecordBatch.from_arrays(
                [pa.nulls(PARTS, pa.int64()), pa.nulls(PARTS, pa.int64()), pa.nulls(PARTS, pa.binary()), pa.array(range(PARTS), pa.int32()), pa.array([lane] * PARTS, pa.int32()), pa.array(blobs, pa.binary())],
                names=["doc_id", "n", "set_key", "part", "lane", "counts"],
            )

    return run


def _sum_counts(table: pa.Table) -> pa.Table:
    total = sum(np.frombuffer(b, dtype="<u4").astype(np.int64) for b in table["counts"].to_pylist())
    return pa.table({"part": pa.array([table["part"][0].as_py()], pa.int32()), "lane": pa.array([table["lane"][0].as_py()], pa.int32()), "counts": pa.array([np.minimum(total, 0xFFFFFFFF).astype("<u4").tobytes()], pa.binary())})


def count_table(first: DataFrame) -> np.ndarray:
    """Eight times the binary logarithm of every hashed counter (two bytes each)."""
    rows = first.filter("part is not null").select("part", "lane", "counts")
    last = rows.agg(F.max("lane")).first()[0] or 0
    while last:  # a tree of sums: one task holds FAN_IN blobs of a part, however many tasks wrote one
        rows = rows.withColumn("lane", F.floor(F.col("lane") / FAN_IN).cast("int")).groupBy("part", "lane").applyInArrow(_sum_counts, "part int, lane int, counts binary")
        last //= FAN_IN
    total = np.zeros(COUNTERS, dtype=np.int64)
    size = COUNTERS // PARTS
    for r in rows.collect():  # PARTS rows
        total[r.part * size : (r.part + 1) * size] = np.frombuffer(r.counts, dtype="<u4")
    return np.round(8 * np.log2(total + 1)).astype(np.uint16)


def _second_pass(k: int, percent: int, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in slices(batches, "text", 1 << 20):
            sets = shingle_sets([t or "" for t in batch.column(1).to_pylist()], k)
            ids, ns, bits, prefixes = [], [], [], []
            for doc, s in zip(batch.column(0).to_pylist(), sets):
                if not len(s) or doc is None:
                    continue
                rank = np.argsort(table[(s & np.uint64(COUNTERS - 1)).astype(np.int64)], kind="stable")
                ids.append(doc)
                ns.append(len(s))
                bits.append(parity_bitmap(s))
                prefixes.append(s[rank[: prefix_length(len(s), percent)]].view(np.int64))
            lengths = np.concatenate([[0], np.cumsum([len(p) for p in prefixes])]).astype(np.int32)
            flat = pa.array(np.concatenate(prefixes) if prefixes else np.zeros(0, np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, pa.int64()), pa.array(ns, pa.int64()), pa.array(band(np.array(ns, dtype=np.int64), percent), pa.int64()), pa.array(bits, pa.binary()), pa.ListArray.from_arrays(pa.array(lengths), flat)],
                names=["id", "n", "band", "bits", "prefix"],
            )

    return run


# ---------------------------------------------------------------- pairs


def _bits(blob: bytes) -> np.ndarray:
    return np.frombuffer(blob, dtype=np.uint64)


def _bitmap_filter(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, na, nb, bits_a, bits_b = (batch.column(i).to_pylist() for i in range(6))
            keep = []
            for n, m, x, y in zip(na, nb, bits_a, bits_b):
                x, y = _bits(x), _bits(y)
                w = min(len(x), len(y))
                differ = int(np.bitwise_count(fold(x, w) ^ fold(y, w)).sum())
                keep.append((n + m - differ) // 2 >= least_overlap(n, m, percent))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def _exact(k: int, percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: OrderedDict[str, np.ndarray] = OrderedDict()
        held = 0

        def sets_of(texts: list[str]) -> dict[str, np.ndarray]:
            nonlocal held
            new = [t for t in dict.fromkeys(texts) if t not in kept]
            out = {t: kept[t] for t in texts if t in kept}
            for t, s in zip(new, shingle_sets(new, k)):
                out[t] = kept[t] = s
                held += s.nbytes
            while held > 64 << 20:
                held -= kept.popitem(last=False)[1].nbytes
            return out

        for batch in batches:
            for part in slices(iter([batch]), "text_a", 1 << 20):
                ta, tb = part.column(2).to_pylist(), part.column(3).to_pylist()
                sets = sets_of([t or "" for t in ta + tb])
                ok = []
                for x, y in zip(ta, tb):
                    x, y = sets[x or ""], sets[y or ""]
                    both = np.intersect1d(x, y, assume_unique=True).size
                    ok.append(both > 0 and both >= least_overlap(len(x), len(y), percent))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1)], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return run


def verified(spark: SparkSession, pairs: DataFrame, signatures: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """Of candidate pairs (a, b), those that link; bit counts first, then whole texts."""
    side = lambda s: signatures.select(F.col("id").alias(s), F.col("n").alias(f"n_{s}"), F.col("bits").alias(f"bits_{s}"))
    with_bits = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "n_b", "bits_a", "bits_b")
    close = stored(spark, with_bits.mapInArrow(_bitmap_filter(percent), "a long, b long"), "close-pairs")
    nodes = close.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    texts = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    texts = stored(spark, texts.join(nodes.hint("shuffle_hash"), "doc_id", "left_semi"), "pair-texts")
    side = lambda s: texts.select(F.col("doc_id").alias(s), F.col("text").alias(f"text_{s}"))
    full = close.join(side("a"), "a").join(side("b"), "b").select("a", "b", "text_a", "text_b")
    return stored(spark, full.mapInArrow(_exact(k, percent), "a long, b long").distinct(), "links")


def _tile_pairs(percent: int, best: int | None):
    def pairs_of(ids, ns, comps, sides, bits):
        """Candidate pairs of one tile that pass size and bit counts; ``best`` per component, or all."""
        order = np.argsort(ns, kind="stable")
        ids, ns, comps, sides = ids[order], ns[order], comps[order], sides[order]
        bits = [bits[i] for i in order]
        left, right, share = [], [], []
        for i in range(len(ids) - 1):
            stop = np.searchsorted(ns, ns[i] * 100 // percent, side="right")
            j = np.arange(i + 1, stop)
            j = j[(comps[j] != comps[i]) & ((sides[j] != sides[i]) | (sides[i] < 0))]
            if not len(j):
                continue
            w = len(bits[i])
            near = np.stack([fold(bits[x], w) for x in j])
            differ = np.bitwise_count(near ^ fold(bits[i], near.shape[1])).sum(axis=1, dtype=np.int64)
            need = -(-percent * (ns[i] + ns[j]) // (100 + percent))
            ok = (ns[i] + ns[j] - differ) // 2 >= need
            left.append(np.full(int(ok.sum()), i))
            right.append(j[ok])
            share.append(differ[ok] / (ns[i] + ns[j[ok]]))
        if not left:
            return
        left, right = np.concatenate(left), np.concatenate(right)
        used: dict[int, int] = {}
        for e in np.argsort(np.concatenate(share), kind="stable") if best else range(len(left)):
            i, x = left[e], right[e]
            if best:
                a, b = int(comps[i]), int(comps[x])
                if used.get(a, 0) >= best and used.get(b, 0) >= best:
                    continue
                used[a], used[b] = used.get(a, 0) + 1, used.get(b, 0) + 1
            yield min(ids[i], ids[x]), max(ids[i], ids[x])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, key, found = [], None, set()

        def emit():
            ids, ns, comps, sides = (np.array([r[i] for r in held], dtype=np.int64) for i in range(1, 5))
            found.update(pairs_of(ids, ns, comps, sides, [_bits(r[5]) for r in held]))

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array([int(x) for x, _ in found], pa.int64()), pa.array([int(y) for _, y in found], pa.int64())], names=["a", "b"])
            found.clear()
            return out

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if row[0] != key:
                    if len(held) > 1:
                        emit()
                    held, key = [], row[0]
                    if len(found) > 20_000:
                        yield flush()
                held.append(row)
        if len(held) > 1:
            emit()
        yield flush()

    return run


def tiles(postings: DataFrame, parts: DataFrame) -> DataFrame:
    """Rows of the tiles that can hold a pair across components: tile, id, n, comp, side.

    ``postings`` has token, id, n, band; ``parts`` node and component.
    """
    blocks = lambda c: F.ceil(F.col(c) / F.lit(TILE)).cast("int")
    rows = postings.join(parts.select(F.col("node").alias("id"), "component"), "id", "left").select("token", "id", "n", F.coalesce("component", "id").alias("comp"))
    sizes = rows.groupBy("token", "comp").agg(F.count(F.lit(1)).alias("c"))
    whole = sizes.groupBy("token").agg(F.max_by("comp", F.struct("c", "comp")).alias("main"), F.max("c").alias("n_main"), (F.sum("c") - F.max("c")).alias("n_other")).filter("n_other > 0")
    whole = stored(postings.sparkSession, whole.select("token", "main", blocks("n_main").alias("bm"), blocks("n_other").alias("bo"), (F.col("n_main") + F.col("n_other") <= TILE).alias("one")), "mixed-tokens")
    rows = rows.join(whole, "token")
    is_main = F.col("comp") == F.col("main")
    mine = F.pmod(F.xxhash64("id"), F.when(is_main, F.col("bm")).otherwise(F.col("bo"))).cast("int")
    every = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    # A tile is (kind, x, y): main block x with other block y, or other blocks x <= y.
    with_main = F.when(is_main, F.transform(every("bo"), lambda y: F.struct(F.lit(0).alias("kind"), mine.alias("x"), y.alias("y"), F.lit(0).alias("side")))).otherwise(
        F.transform(every("bm"), lambda x: F.struct(F.lit(0).alias("kind"), x.alias("x"), mine.alias("y"), F.lit(1).alias("side")))
    )
    others = F.when(
        ~is_main,
        F.transform(every("bo"), lambda y: F.struct(F.lit(1).alias("kind"), F.least(mine, y).alias("x"), F.greatest(mine, y).alias("y"), F.when(mine == y, -1).otherwise(F.when(mine < y, 0).otherwise(1)).alias("side"))),
    )
    dealt = F.when(F.col("one"), F.array(F.struct(F.lit(2).alias("kind"), F.lit(0).alias("x"), F.lit(0).alias("y"), F.lit(-1).alias("side")))).otherwise(F.concat(with_main, F.coalesce(others, F.expr("cast(array() as array<struct<kind:int,x:int,y:int,side:int>>)"))))
    return rows.select("token", "id", "n", "comp", F.explode(dealt).alias("t")).select(F.xxhash64("token", "t.kind", "t.x", "t.y").alias("tile"), "id", "n", "comp", F.col("t.side").alias("side"))


def similar(spark: SparkSession, docs: DataFrame, k: int = 4, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of ``docs``."""
    ship(spark)
    rows = spread(docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text")))
    first = stored(spark, rows.mapInArrow(_first_pass(k), "doc_id long, n long, set_key binary, part int, lane int, counts binary"), "sets")
    shared = spark.sparkContext.broadcast(count_table(first))
    members = first.filter("part is null").select("doc_id", "n", "set_key")
    classes = stored(spark, members.filter("set_key is not null and doc_id is not null").groupBy("set_key").agg(F.min("doc_id").alias("id")), "classes")
    chosen = classes.select("id").distinct()
    signatures = rows.mapInArrow(_second_pass(k, percent, shared), "id long, n long, band long, bits binary, prefix array<bigint>")
    signatures = stored(spark, signatures.join(chosen.hint("shuffle_hash"), "id", "left_semi"), "signatures")

    postings = signatures.select(F.explode("prefix").alias("token"), "id", F.col("n").cast("int").alias("n"), F.col("band").cast("int").alias("band"))
    frequent = postings.groupBy("token").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("token")
    postings = stored(spark, postings.join(stored(spark, frequent, "tokens"), "token"), "postings")

    heads = postings.groupBy("token", "band").agg(F.min("id").alias("head"))
    near = postings.select("token", "id", "n", F.explode(F.array(F.col("band"), F.col("band") - 1)).alias("band")).join(heads, ["token", "band"])
    stars = near.filter("id <> head").select(F.least("id", "head").alias("a"), F.greatest("id", "head").alias("b")).distinct()
    links = verified(spark, stored(spark, stars, "stars"), signatures, docs, k, percent)
    parts = stored(spark, connected(spark, links), "components")
    for best in BEST:
        tiled = tiles(postings, parts).join(signatures.select("id", "bits"), "id").select("tile", "id", "n", "comp", "side", "bits")
        dealt = tiled.repartition("tile").sortWithinPartitions("tile")
        cross = stored(spark, dealt.mapInArrow(_tile_pairs(percent, best), "a long, b long").distinct(), "tile-pairs")
        if cross.isEmpty():  # no pair that could link is left apart
            break
        links = links.unionByName(verified(spark, cross, signatures, docs, k, percent))
        parts = stored(spark, connected(spark, links), "components")
    joined = parts.withColumnRenamed("node", "id")
    labels = classes.join(joined, "id", "left").select("set_key", F.coalesce("component", "id").alias("component_id"))
    return members.join(labels, "set_key", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))


def deduplicate(spark: SparkSession, docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` that stay: of each component the document with the smallest id, all columns."""
    own = fresh(docs, "_kept")
    kept = similar(spark, docs, k, percent).filter("doc_id = component_id or doc_id is null").select(F.col("doc_id").alias(own)).distinct()
    return docs.join(kept, docs["doc_id"].eqNullSafe(F.col(own)), "left_semi")


ORACLE_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words
  FROM documents),
g AS (
  SELECT DISTINCT doc_id, array_to_string(words[i + 1 : i + 4], ' ') AS gram
  FROM (SELECT doc_id, words, unnest(range(greatest(len(words) - 3, 1))) AS i FROM w WHERE len(words) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
pairs AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS both_have
          FROM g a JOIN g b ON a.gram = b.gram AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id),
links AS (SELECT x, y FROM pairs JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y
          WHERE 100 * both_have >= 85 * (p.n + q.n - both_have)),
reach AS (SELECT doc_id AS node, doc_id AS seen FROM n
          UNION SELECT r.node, l.y FROM reach r JOIN links l ON r.seen = l.x)
SELECT d.doc_id, coalesce(max(n.n), 0)::BIGINT AS n_shingles, coalesce(min(r.seen), d.doc_id) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN reach r ON r.node = d.doc_id
GROUP BY d.doc_id
"""
