"""Removal of repeated byte strings across the corpus by bucket-pointer refinement.

Every byte covered by a string of ``LENGTH`` bytes that starts at two places or
more (documents do not join) is removed.  The suffixes of the whole corpus are
too many to sort as rows, so they move in buckets:

1.  A window (a start and its ``LENGTH`` bytes) belongs to the q-gram with the
    smallest hash among its first ``SPAN`` q-grams, its *anchor*; which one is
    decided by the window's bytes alone.  Neighbouring windows share anchors, so a
    document is a row per anchor: the range of its windows, an identifier of the
    bytes that all of them hold (*core*) and of all their bytes (*hull*).  Equal
    windows have equal cores, so the core is the first bucket.
2.  A core at one place only is dropped.  Rows of a core that share one hull are
    repeated as a whole; a hull found twice is too.  Both are counts that combine
    on the map side.
3.  What remains are single hulls beside others under one core.  One context per
    hull is cut from the texts, and the windows of a core's contexts are sorted by
    bucket-pointer refinement (:mod:`suffix_array`), from q-grams of a quarter of
    ``LENGTH`` to ``LENGTH`` bytes; a bucket of weight two or more is repeated.
4.  A core with more than ``MAX_GROUP`` contexts is first refined across tasks:
    its range of windows is cut in four, each part with its own core and hull, and
    steps 2 and 3 are taken again on the parts, down to single windows.

Identifiers are 64-bit hashes; two of them (core and hull) must collide at once
for a wrong match.

Defined results: null text is empty; texts are their UTF-8 bytes, and removal may
split a character; a text shorter than ``LENGTH`` loses nothing; rows that repeat
a ``doc_id`` are separate texts; a null ``doc_id`` is carried; extra columns pass
unread; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import discard, ship, slices, split_join, spread, stored
from .shingles import RADIX, _power_table, mix
from .suffix_array import bucket_ids

LENGTH = 400
SPAN = 200
GRAM = 32
PIECE = 1 << 20
MAX_GROUP = 4096
PARTS = (64, 16, 4, 1)

_PLACE = (1 << 23) - 1


class Hashes:
    """Hashes of any byte range of a buffer, from one running sum."""

    def __init__(self, data: np.ndarray):
        self.total = np.zeros(len(data) + 1, dtype=np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _power_table(len(data) + 1, False)[: len(data)], out=self.total[1:])
        self.inverse = _power_table(len(data) + 1, True)

    def grams(self, q: int) -> np.ndarray:
        """The hash of the q bytes at every place."""
        n = len(self.total) - q
        return mix((self.total[q:] - self.total[:n]) * self.inverse[:n])

    def of(self, start: np.ndarray, end: np.ndarray, salt: np.ndarray | int = 0) -> np.ndarray:
        raw = (self.total[end] - self.total[start]) * self.inverse[start]
        return mix(raw + (np.asarray(end - start, dtype=np.uint64) * RADIX) ^ np.asarray(salt, dtype=np.uint64))


def anchor_runs(data: np.ndarray, ends: np.ndarray, length: int = LENGTH, span: int = SPAN, gram: int = GRAM):
    """(lo, hi, anchor) of the runs of windows that share an anchor; ``ends`` closes each text of the buffer."""
    n = len(data)
    if n < length:
        return (np.zeros(0, dtype=np.int64),) * 3
    at = np.arange(n - gram + 1, dtype=np.uint64)
    packed = (Hashes(data).grams(gram) & ~np.uint64(_PLACE)) | at
    full = -(-(len(packed) + span) // span) * span
    grid = np.full(full, np.iinfo(np.uint64).max, dtype=np.uint64)
    grid[: len(packed)] = packed
    grid = grid.reshape(-1, span)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    behind = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    begin = np.concatenate([[0], ends[:-1]])
    valid = np.zeros(n + 1, dtype=np.int8)
    fits = ends - begin >= length
    valid[begin[fits]] += 1
    valid[ends[fits] - length + 1] -= 1
    p = np.flatnonzero(np.cumsum(valid[:n]))
    a = (np.minimum(behind[p], ahead[p + span - 1]) & np.uint64(_PLACE)).astype(np.int64)
    if not len(p):
        return p, p, p
    cut = np.flatnonzero(a[1:] != a[:-1]) + 1
    first = np.concatenate([[0], cut])
    last = np.concatenate([cut - 1, [len(p) - 1]])
    return p[first], p[last], a[first]


def _pieces(texts: list[bytes], length: int) -> Iterator[tuple[int, int, bytes]]:
    """(text number, place in it, bytes): long texts in overlapping pieces."""
    for i, t in enumerate(texts):
        for s in range(0, max(1, len(t) - length + 1), PIECE):
            yield i, s, t[s : s + PIECE + length - 1]


def _anchors(length: int, span: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", PIECE):
            texts = [(t or "").encode("utf-8", "surrogatepass") for t in batch.column(2).to_pylist()]
            doc, row = batch.column(0), batch.column(1)
            group, size = [], 0
            for piece in _pieces(texts, length):
                if group and size + len(piece[2]) > 2 * PIECE:
                    yield rows(group, doc, row)
                    group, size = [], 0
                group.append(piece)
                size += len(piece[2])
            if group:
                yield rows(group, doc, row)

    def rows(group, doc, row) -> pa.RecordBatch:
        data = np.frombuffer(b"".join(b for _, _, b in group), dtype=np.uint8)
        ends = np.cumsum([len(b) for _, _, b in group])
        lo, hi, a = anchor_runs(data, ends, length, span)
        if len(lo):
            h = Hashes(data)
            core = h.of(a, a + length - span + 1)
            hull = h.of(lo, hi + length, (a - lo) * 1024 + (hi - lo) + 1)
        else:
            core = hull = np.zeros(0, dtype=np.uint64)
        which = np.searchsorted(ends, lo, side="right")
        text_no = np.array([i for i, _, _ in group], dtype=np.int64)[which]
        shift = np.array([s for _, s, _ in group], dtype=np.int64)[which] - np.concatenate([[0], ends[:-1]])[which]
        return pa.RecordBatch.from_arrays(
            [doc.take(pa.array(text_no)), row.take(pa.array(text_no)), pa.array((lo + shift).astype(np.int32)), pa.array((hi + shift).astype(np.int32)), pa.array((a - lo).astype(np.int32)), pa.array(core.view(np.int64)), pa.array(hull.view(np.int64))],
            names=["doc_id", "row_hash", "lo", "hi", "off", "core", "hull"],
        )

    return run


PLACE = ["doc_id", "row_hash", "lo", "hi"]


def _cut_contexts(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(8)]
            docs, rows = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for doc, row, text, spots in zip(docs, rows, batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                raw = text.encode("utf-8", "surrogatepass")
                for s in spots:
                    for column, value in zip(out, (s["core"], s["m"], doc, row, s["lo"], s["hi"], s["off"], raw[s["lo"] : s["hi"] + length])):
                        column.append(value)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(out, kinds)], names=["core", "m", "doc_id", "row_hash", "lo", "hi", "off", "context"])

    return run


def _sort_groups(length: int, budget: int = 1 << 21):
    """Windows of whole cores, sorted together; yields the repeated ranges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0
        for batch in batches:
            for r in zip(*(batch.column(i).to_pylist() for i in range(7))):
                if size > budget and r[0] != held[-1][0]:
                    yield repeated(held)
                    held, size = [], 0
                held.append(r)
                size += len(r[6])
        if held:
            yield repeated(held)

    def repeated(held: list[tuple]) -> pa.RecordBatch:
        text = np.frombuffer(b"".join(r[6] for r in held), dtype=np.uint8)
        ends = np.cumsum([len(r[6]) for r in held])
        count = np.array([r[5] - r[4] + 1 for r in held])
        owner = np.repeat(np.arange(len(held)), count)
        inside = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
        starts = np.concatenate([[0], ends[:-1]])[owner] + inside
        h = Hashes(text)
        ids = bucket_ids(text, starts, length, length // 4, lambda at: h.of(at, at + length // 4))
        weight = np.bincount(ids, weights=np.array([r[1] for r in held], dtype=np.float64)[owner])
        hit = np.flatnonzero((weight[ids] >= 2) & (np.array([r[1] for r in held])[owner] == 1))
        cut = np.flatnonzero((owner[hit][1:] != owner[hit][:-1]) | (hit[1:] != hit[:-1] + 1)) + 1
        first = hit[np.concatenate([[0], cut])] if len(hit) else hit
        last = hit[np.concatenate([cut - 1, [len(hit) - 1]])] if len(hit) else hit
        return pa.RecordBatch.from_arrays(
            [
                pa.array([held[i][2] for i in owner[first]], pa.int64()),
                pa.array([held[i][3] for i in owner[first]], pa.int32()),
                pa.array([held[i][4] + int(k) for i, k in zip(owner[first], inside[first])], pa.int32()),
                pa.array([held[i][4] + int(k) for i, k in zip(owner[last], inside[last])], pa.int32()),
            ],
            names=PLACE,
        )

    return run


def _split(length: int, part: int):
    """Cut each context's windows into parts by their distance from the anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(9)]
            held = list(zip(*(batch.column(i).to_pylist() for i in range(8))))
            text = np.frombuffer(b"".join(r[7] for r in held), dtype=np.uint8)
            h = Hashes(text)
            base = 0
            for core, m, doc, row, lo, hi, off, context in held:
                # distances from the anchor run from off (window lo) down to off - (hi - lo)
                for k in range((off - hi + lo) // part, off // part + 1):
                    far, near = min(off, k * part + part - 1), max(off - hi + lo, k * part)
                    start = base + off - far
                    inner = h.of(np.array([base + off - k * part]), np.array([base + off - (k * part + part - 1) + length]), k + 1)[0]
                    outer = h.of(np.array([start]), np.array([base + off - near + length]), far * 1024 + near + 1)[0]
                    key = mix(np.array([(core * int(RADIX) ^ int(inner)) & 0xFFFFFFFFFFFFFFFF], dtype=np.uint64))[0]
                    row_out = (int(key.view(np.int64)), m, doc, row, lo + off - far, lo + off - near, far, context[off - far : off - near + length], int(outer.view(np.int64)))
                    for column, value in zip(out, row_out):
                        column.append(value)
                base += len(context)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(out, kinds)], names=["core", "m", "doc_id", "row_hash", "lo", "hi", "off", "context", "hull"])

    return run


CONTEXT = "core long, m long, doc_id long, row_hash int, lo int, hi int, off int, context binary"


def _undecided(spark: SparkSession, rows: DataFrame, weight) -> tuple[DataFrame, DataFrame]:
    """(ranges repeated as a whole, one row per hull that needs its windows compared).

    ``rows`` has core, hull, the place and maybe more; ``weight`` is a row's number of occurrences.
    """
    cores = stored(spark, rows.groupBy("core").agg(F.sum(weight).alias("c"), F.min("hull").alias("low"), F.max("hull").alias("high")).filter("c > 1"), "cores")
    many = stored(spark, split_join(spark, rows, cores.select("core", "c", (F.col("low") == F.col("high")).alias("one_hull")), ["core"], "c"), "shared-cores")
    discard(spark, cores)
    mixed = many.filter("not one_hull")
    place = F.struct(*PLACE, "off")
    hulls = stored(spark, mixed.groupBy("core", "hull").agg(F.sum(weight).alias("m"), F.min(place).alias("at")), "hulls")
    again = split_join(spark, mixed, hulls.filter("m > 1").select("core", "hull", "m"), ["core", "hull"], "m")
    whole = many.filter("one_hull").select(*PLACE).unionByName(again.select(*PLACE))
    lone = stored(spark, hulls.filter("m = 1").select("core").distinct(), "open-cores")
    return whole, stored(spark, hulls.join(lone, "core", "left_semi"), "open-hulls")


def _by_size(spark: SparkSession, contexts: DataFrame, limit: int) -> tuple[DataFrame, DataFrame | None]:
    """(contexts of cores that one task can sort, contexts of larger cores or None)."""
    large = stored(spark, contexts.groupBy("core").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") > limit).select("core"), "large-cores")
    if large.isEmpty():
        return contexts, None
    return contexts.join(large, "core", "left_anti"), contexts.join(large, "core", "left_semi")


def repeated_ranges(spark: SparkSession, rows: DataFrame, length: int = LENGTH, span: int = SPAN, max_group: int = MAX_GROUP) -> DataFrame:
    """doc_id, row_hash, lo, hi: starts lo..hi of repeated windows; ``rows`` has doc_id, row_hash, text."""
    schema = "doc_id long, row_hash int, lo int, hi int, off int, core long, hull long"
    anchors = stored(spark, rows.mapInArrow(_anchors(length, span), schema), "anchors")
    found, reps = _undecided(spark, anchors, F.lit(1))
    discard(spark, anchors)
    spots = reps.select("core", "m", F.col("at.doc_id").alias("doc_id"), F.col("at.row_hash").alias("row_hash"), F.col("at.lo").alias("lo"), F.col("at.hi").alias("hi"), F.col("at.off").alias("off"))
    per_text = spots.groupBy("doc_id", "row_hash").agg(F.collect_list(F.struct("core", "m", "lo", "hi", "off")).alias("spots"))
    per_text = per_text.withColumnRenamed("doc_id", "_d").withColumnRenamed("row_hash", "_r")
    cut = rows.join(per_text.hint("shuffle_hash"), F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("row_hash") == F.col("_r"))).select("doc_id", "row_hash", "text", "spots")
    contexts = stored(spark, cut.mapInArrow(_cut_contexts(length), CONTEXT).dropDuplicates(["core", *PLACE]), "contexts")
    tables = [found]
    for part in (*PARTS, None):
        small, contexts = _by_size(spark, contexts, max_group)
        dealt = small.select("core", "m", *PLACE, "context").repartition("core").sortWithinPartitions("core")
        tables.append(dealt.mapInArrow(_sort_groups(length), "doc_id long, row_hash int, lo int, hi int"))
        if contexts is None:
            break
        parts = stored(spark, contexts.mapInArrow(_split(length, part), CONTEXT + ", hull long"), "parts")
        whole, reps = _undecided(spark, parts.drop("context"), F.col("m"))
        tables.append(whole)
        # by place, not by hull: a place is one row, a hull may be a third of them
        keep = reps.select(F.col("core").alias("_core"), F.col("m").alias("_m"), *[F.col(f"at.{c}").alias(f"_{c}") for c in PLACE])
        same = F.col("core") == F.col("_core")
        for c in PLACE:
            same = same & F.col(c).eqNullSafe(F.col(f"_{c}"))
        contexts = stored(spark, parts.join(keep, same).select("core", F.col("_m").alias("m"), *PLACE, "off", "context"), "contexts")
    out = tables[0]
    for t in tables[1:]:
        out = out.unionByName(t)
    return out


def _cover(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(iter([whole]), "text", 1 << 21):
                out: list[list] = [[], [], [], [], []]
                for doc, text, ranges in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                    raw = (text or "").encode("utf-8", "surrogatepass")
                    kept, removed, spans, at = [], 0, 0, 0
                    if ranges:
                        pair = np.array([(r["lo"], r["hi"] + length) for r in ranges], dtype=np.int64)
                        pair = pair[np.argsort(pair[:, 0], kind="stable")]
                        reach = np.maximum.accumulate(pair[:, 1])
                        first = np.concatenate([[True], pair[1:, 0] > reach[:-1]])
                        begin, end = pair[first, 0], reach[np.concatenate([np.flatnonzero(first)[1:] - 1, [len(pair) - 1]])]
                        spans, removed = len(begin), int((end - begin).sum())
                        for b, e in zip(begin.tolist(), end.tolist()):
                            kept.append(raw[at:b])
                            at = e
                    kept.append(raw[at:])
                    for column, value in zip(out, (doc, len(raw), removed, spans, b"".join(kept))):
                        column.append(value)
                kinds = [pa.int64()] * 4 + [pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(out, kinds)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return run


def remove_repeats(spark: SparkSession, docs: DataFrame, length: int = LENGTH, span: int = SPAN, max_group: int = MAX_GROUP) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (the remaining bytes) of every row."""
    ship(spark)
    text = F.coalesce(docs["text"].cast("string"), F.lit(""))
    rows = spread(docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.hash(text).alias("row_hash"), text.alias("text")))
    ranges = stored(spark, repeated_ranges(spark, rows, length, span, max_group), "ranges")
    merged = ranges.groupBy(F.col("doc_id").alias("_d"), F.col("row_hash").alias("_r")).agg(F.collect_list(F.struct("lo", "hi")).alias("ranges"))
    joined = rows.join(merged.hint("shuffle_hash"), F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("row_hash") == F.col("_r")), "left")
    return joined.select("doc_id", "text", "ranges").mapInArrow(_cover(length), "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def digest(spark: SparkSession, docs: DataFrame) -> DataFrame:
    return remove_repeats(spark, docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
