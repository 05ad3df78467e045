"""Graphs built from the tables: nodes (id, feat, label, split) and edges (src, dst, w)."""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import ship, spread
from .tables import load

SECOND = 10_000_000
"""Added to the identifiers of a graph's second node type."""


@dataclass(frozen=True)
class Graph:
    nodes: DataFrame
    edges: DataFrame


def split_of(id_: Column) -> Column:
    r = F.pmod(id_, F.lit(10))
    return F.when(r <= 4, "train").when(r == 5, "val").otherwise("test")


def as_nodes(df: DataFrame) -> DataFrame:
    return df.select(F.col("id").cast("long").alias("id"), F.col("feat").cast("array<double>").alias("feat"), F.col("label").cast("int").alias("label"), split_of(F.col("id").cast("long")).alias("split"))


def as_edges(df: DataFrame) -> DataFrame:
    return df.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.lit(1.0).alias("w"))


def symmetrize(edges: DataFrame, self_loops: bool = False) -> DataFrame:
    """Both directions of every edge, once."""
    both = edges.select("src", "dst", "w").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    if not self_loops:
        both = both.filter("src <> dst")
    return both.groupBy("src", "dst").agg(F.max("w").alias("w"))


def project(bipartite: DataFrame, via: str = "dst", keep: str = "src", max_degree: int | None = None) -> DataFrame:
    """Edges between nodes of one type that meet in a node of the other; ``max_degree`` leaves out crowded meeting points."""
    b = bipartite.select(F.col(keep).alias("n"), F.col(via).alias("v")).distinct()
    if max_degree:
        b = b.join(b.groupBy("v").count().filter(F.col("count") <= max_degree).select("v"), "v")
    pairs = b.select("v", F.col("n").alias("src")).join(b.select("v", F.col("n").alias("dst")), "v").filter("src <> dst")
    return as_edges(pairs.select("src", "dst").distinct())


def degree(edges: DataFrame) -> DataFrame:
    """id, in_degree, out_degree."""
    i = edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("in_degree"))
    o = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("out_degree"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    return i.join(o, "id", "full").select("id", zero("in_degree"), zero("out_degree"))


def _part_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "part")
    kind = F.pmod(F.crc32(F.encode("p_type", "UTF-8")), F.lit(8)).cast("int")
    feat = F.array(F.lit(1.0), F.col("p_size") / 50.0, F.col("p_retailprice") / 2000.0, *[F.when(F.pmod(F.crc32(F.encode("p_brand", "UTF-8")), F.lit(5)) == i, 1.0).otherwise(0.0) for i in range(5)])
    return p.select(F.col("p_partkey").alias("id"), feat.alias("feat"), kind.alias("label"))


def copurchase_parts(spark: SparkSession, sf_dir: str) -> Graph:
    """Parts bought in one order."""
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = li.select("l_orderkey", F.col("l_partkey").alias("src")).join(li.select("l_orderkey", F.col("l_partkey").alias("dst")), "l_orderkey").filter("src <> dst")
    return Graph(as_nodes(_part_nodes(spark, sf_dir)), as_edges(pairs.select("src", "dst").distinct()))


def part_supplier(spark: SparkSession, sf_dir: str, quantity: float = 40, discount: float = 0.08) -> Graph:
    """Parts and suppliers that meet in a large, discounted line item; both directions."""
    li = load(spark, sf_dir, "lineitem").filter((F.col("l_quantity") >= quantity) & (F.col("l_discount") >= discount))
    pairs = li.select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + SECOND).alias("dst")).distinct()
    back = pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    s = load(spark, sf_dir, "supplier")
    supp = s.select((F.col("s_suppkey") + SECOND).alias("id"), F.array(F.lit(0.0), F.col("s_nationkey") / 25.0, F.col("s_acctbal") / 10000.0, *[F.lit(0.0)] * 5).alias("feat"), F.lit(None).cast("int").alias("label"))
    return Graph(as_nodes(_part_nodes(spark, sf_dir).unionByName(supp)), as_edges(pairs.unionByName(back)))


#: Code points whose pairs have a table; pairs with others are looked up one kind at a time.
NEAR = 256
#: Rows whose texts are taken apart together.
ROWS = 500


#: Characters that are worked on together: arrays of them stay in a core's cache.
CHARS = 1 << 16


def _pair_bucket(a: int, b: int, buckets: int) -> int:
    return zlib.crc32((chr(a) + chr(b)).encode("utf-8", "surrogatepass")) % buckets


@lru_cache
def _near_lanes(buckets: int) -> np.ndarray:
    """For every eight buckets a table by pair of near code points: a one in the byte of the pair's bucket."""
    bucket = np.array([_pair_bucket(a, b, buckets) for a in range(NEAR) for b in range(NEAR)], dtype=np.int64)
    one = np.uint64(1) << (np.uint64(8) * (bucket % 8).astype(np.uint64))
    return np.stack([np.where(bucket // 8 == k, one, np.uint64(0)) for k in range(-(-buckets // 8))])


def _slices(sizes: list[int], most: int) -> Iterator[slice]:
    """Runs of entries with about ``most`` in all; one that is larger stands by itself."""
    start, total = 0, 0
    for i, size in enumerate(sizes):
        if i > start and total + size > most:
            yield slice(start, i)
            start, total = i, 0
        total += size
    if start < len(sizes):
        yield slice(start, len(sizes))


def _bigram_counts(buckets: int):
    """Rows (id, text) to (id, a count of lower-cased character pairs for every bucket of their CRC-32), texts with a pair only."""

    def counts(texts: list[str], kinds: dict[int, int]) -> np.ndarray:
        c = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        size = np.array([len(t) for t in texts])
        some = np.flatnonzero(size > 1)
        out = np.zeros((len(texts), buckets), dtype=np.int64)
        if not len(some):
            return out
        ends = np.cumsum(size)
        begin, n = ends[some] - size[some], size[some] - 1  # a text's pairs
        far = np.flatnonzero(c >= NEAR)
        code = ((c[:-1] << np.uint32(8)) | (c[1:] & np.uint32(NEAR - 1))) & np.uint32(NEAR * NEAR - 1)
        beside = np.unique(np.concatenate([far, far - 1])) if len(far) else far
        none = np.concatenate([beside, ends - 1])  # no pair, or none of the table
        none = none[(none >= 0) & (none < len(code))]
        # a byte counts to 255: the pairs of a text are added up 255 at a time
        runs = -(-n // 255)
        first = np.cumsum(runs) - runs
        at = np.repeat(begin - 255 * first, runs) + 255 * np.arange(runs.sum())
        for k, table in enumerate(_near_lanes(buckets)):
            lanes = table.take(code)
            lanes[none] = 0
            sums = np.add.reduceat(lanes, at).view(np.uint8).reshape(-1, 8).astype(np.int64)  # to the next run: what is between is no pair
            out[some, 8 * k : 8 * k + 8] = np.add.reduceat(sums, first, axis=0)[:, : buckets - 8 * k]
        if len(far):
            doc = np.searchsorted(ends, beside, side="right")
            far = beside[(beside >= 0) & (beside + 1 < ends[np.minimum(doc, len(ends) - 1)])]
            pairs, which = np.unique(c[far].astype(np.uint64) << np.uint64(32) | c[far + 1], return_inverse=True)
            for p in pairs.tolist():
                if p not in kinds:
                    kinds[p] = _pair_bucket(p >> 32, p & 0xFFFFFFFF, buckets)
            bucket = np.array([kinds[p] for p in pairs.tolist()], dtype=np.int64)[which]
            out += np.bincount(np.searchsorted(ends, far, side="right") * buckets + bucket, minlength=len(texts) * buckets).reshape(-1, buckets)
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds: dict[int, int] = {}  # pair of code points to bucket
        for whole in batches:
            for start in range(0, whole.num_rows, ROWS):
                batch = whole.slice(start, ROWS)
                texts = [t.lower() for t in batch.column(1).to_pylist()]
                table = np.concatenate([counts(texts[part], kinds) for part in _slices([len(t) for t in texts], CHARS)])
                out = pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(table[:, k].astype(np.int64)) for k in range(buckets))], names=["id", *(f"c{k}" for k in range(buckets))])
                yield out.filter(pa.array(table.any(axis=1)))

    return run


def _features(noise: float, seed: int):
    """Rows (id, counts) to (id, counts of norm one with noise): the sum of twelve uniforms less six is close to a normal number."""
    from ..functions.vectors import uniforms

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m = np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns[1:]], axis=1)
            x = m / np.sqrt((m * m).sum(axis=1).astype(np.float64))[:, None]
            if noise:
                ids = batch.column(0).to_numpy(zero_copy_only=False)
                for k in range(x.shape[1]):
                    normal = np.full(len(ids), -6.0)
                    for j in range(12):
                        normal += uniforms(ids, k * 12 + j, seed)
                    x[:, k] += noise * normal
            ends = pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(ends, pa.array(x.ravel()))], names=["id", "feat"])

    return run


def _bigram_nodes(docs: DataFrame, buckets: int, noise: float, seed: int) -> DataFrame:
    ship(docs.sparkSession)
    # in arrays: a row per pair of characters would be some hundred rows a line of text, a higher-order function is slow
    columns, id_ = [f"c{k}" for k in range(buckets)], f"id {docs.schema['id'].dataType.simpleString()}"
    counted = spread(docs).filter("id is not null").select("id", "text").mapInArrow(_bigram_counts(buckets), ", ".join([id_, *(f"{c} long" for c in columns)]))
    summed = counted.groupBy("id").agg(*[F.sum(c).alias(c) for c in columns])
    return summed.mapInArrow(_features(noise, seed), f"{id_}, feat array<double>")


GRAM_BUCKETS = 4096
NO_ID = -(1 << 63)


#: Bytes of a word that take part in its hash by table; a longer word gets its MD5.
TABLED = 24
_TABLE = np.frombuffer(hashlib.shake_128(b"words").digest(2 * TABLED * 256 * 8), dtype=np.uint64).reshape(2, -1)


def _word_digests(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(two 64-bit hashes, number of its text) of every word, in order.

    A hash is the sum of random numbers by place and byte (tabulation), so words that differ meet by chance only.
    """
    blobs = [t.encode("utf-8", "surrogatepass") for t in texts]
    done = [(*_chunk_digests(blobs[part]), part.start) for part in _slices([len(b) for b in blobs], CHARS)]
    if not done:
        return np.zeros((0, 2), dtype=np.uint64), np.zeros(0, dtype=np.int64)
    return np.concatenate([d for d, _, _ in done]), np.concatenate([doc + start for _, doc, start in done])


def _chunk_digests(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    c = np.frombuffer(b" ".join([*blobs, b""]), dtype=np.uint8)
    white = np.ones(len(c) + 2, dtype=bool)
    white[1:-1] = (c == 32) | ((c - np.uint8(9)) < 5)  # what bytes.split takes for space
    turns = np.flatnonzero(white[1:] != white[:-1])
    starts, stops = turns[::2], turns[1::2]
    size = stops - starts
    doc = np.searchsorted(np.cumsum([len(b) + 1 for b in blobs]), starts, side="right")
    if not len(size):
        return np.zeros((0, 2), dtype=np.uint64), doc
    begin = np.cumsum(size) - size
    cell = np.arange(size.sum())
    cell -= np.repeat(begin, size)
    np.minimum(cell, TABLED - 1, out=cell)
    cell *= 256
    cell += c[~white[1:-1]]
    out = np.stack([np.add.reduceat(t.take(cell), begin) for t in _TABLE], axis=1)
    for i in np.flatnonzero(size > TABLED).tolist():
        out[i] = np.frombuffer(hashlib.md5(c[starts[i] : stops[i]].tobytes()).digest(), dtype=np.uint64)
    return out, doc


#: Pairs or grams that a task gathers before it deals them.
PAIRS = 1 << 20
DEALT = "bucket int, first binary, second binary, third binary"


def _dealt(bucket: np.ndarray, *columns: np.ndarray) -> pa.RecordBatch:
    """A row per bucket with the bytes of its entries of each column."""
    order = np.argsort(bucket, kind="stable")  # 16 bits: a radix sort
    bucket = bucket[order]
    begin = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]])) if len(bucket) else np.zeros(0, dtype=np.int64)
    offsets = np.append(begin, len(bucket))
    cells = [pa.array(bucket[begin].astype(np.int32))]
    for c in (*columns, *[bucket[:0]] * (3 - len(columns))):
        place = (offsets * c.itemsize if len(c) else 0 * offsets).astype(np.int32)
        cells.append(pa.Array.from_buffers(pa.binary(), len(begin), [None, pa.py_buffer(place), pa.py_buffer(c[order] if len(c) else c)]))
    return pa.RecordBatch.from_arrays(cells, names=["bucket", "first", "second", "third"])


def _by_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[list[bytes]]:
    """The columns of each bucket, put together, from rows sorted by it."""
    key, held = None, []
    for batch in batches:
        for b, *blobs in zip(*(batch.column(i).to_pylist() for i in range(4))):
            if b != key and held:
                yield [b"".join(c) for c in zip(*held)]
                held = []
            key = b
            held.append(blobs)
    if held:
        yield [b"".join(c) for c in zip(*held)]


def _grams(n: int):
    """Rows (id, text) to word n-grams by bucket: digests of 96 bits and ids as packed arrays."""

    def grams(digests: np.ndarray, inside: np.ndarray) -> Iterator[np.ndarray]:
        for half, odd in ((0, 0x9E3779B97F4A7C15), (1, 0xC2B2AE3D27D4EB4F)):
            h = np.zeros(len(inside), dtype=np.uint64)
            for j in range(n):
                h *= np.uint64(odd)
                h += digests[j : j + len(h), half]
                h ^= h >> np.uint64(29)
            h *= np.uint64(0xBF58476D1CE4E5B9)
            h ^= h >> np.uint64(32)
            yield h[inside]

    def dealt(held: list[tuple]) -> pa.RecordBatch:
        h, g, ids = (np.concatenate(c) for c in zip(*held))
        return _dealt((h >> np.uint64(64 - (GRAM_BUCKETS - 1).bit_length())).astype(np.uint16), h, g, ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for whole in batches:
            for start in range(0, whole.num_rows, ROWS):
                batch = whole.slice(start, ROWS)
                own = batch.column(0).fill_null(NO_ID).to_numpy().astype(np.int64)
                texts = batch.column(1).to_pylist()
                for part in _slices([len(t) for t in texts], CHARS):
                    digests, doc = _word_digests(texts[part])
                    if len(doc) < n:
                        continue
                    inside = doc[: len(doc) - n + 1] == doc[n - 1 :]
                    h, g = grams(digests, inside)
                    held.append((h, g.astype(np.uint32), own[part][doc[: len(inside)][inside]]))
                    size += len(h)
                if size >= PAIRS:
                    yield dealt(held)
                    held, size = [], 0
        if held:
            yield dealt(held)

    return run


def _distinct(h: np.ndarray, g: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct (h, g, id), equal digests beside each other and their ids rising."""
    order = np.lexsort((ids, h))
    if ((h[order[1:]] == h[order[:-1]]) & (g[order[1:]] != g[order[:-1]])).any():  # two grams of one first half
        order = np.lexsort((ids, g, h))
    h, g, ids = h[order], g[order], ids[order]
    new = np.ones(len(h), dtype=bool)
    new[1:] = (h[1:] != h[:-1]) | (g[1:] != g[:-1]) | (ids[1:] != ids[:-1])
    return h[new], g[new], ids[new]


def _sorted_distinct(v: np.ndarray) -> np.ndarray:
    v = np.sort(v)
    return v[np.concatenate([[True], v[1:] != v[:-1]])] if len(v) else v


def _distinct_pairs(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs: two places of 32 bits are one number, which sorts faster than two columns."""
    known = None
    if len(a) and (min(a.min(), b.min()) < 0 or max(a.max(), b.max()) >> 31):
        known, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        a, b = at[: len(a)], at[len(a) :]
    a, b = np.divmod(_sorted_distinct(a << 32 | b), 1 << 32)
    return (a, b) if known is None else (known[a], known[b])


def _sharing(most: int):
    """Pairs of documents, the smaller first, that share a gram which 2 to ``most`` of them hold; dealt by the smaller."""

    def pairs(h: np.ndarray, g: np.ndarray, ids: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        # most grams are there once: a sort of the digests alone finds the others, up to those that share 16 bits with them
        rising = np.sort(h)
        twice = np.zeros(1 << 16, dtype=bool)
        twice[rising[1:][rising[1:] == rising[:-1]] >> np.uint64(32) & np.uint64(0xFFFF)] = True
        order = np.flatnonzero(twice[h >> np.uint64(32) & np.uint64(0xFFFF)])
        h, g, ids = _distinct(h[order], g[order], ids[order])
        new = np.ones(len(h), dtype=bool)
        new[1:] = (h[1:] != h[:-1]) | (g[1:] != g[:-1])
        begin = np.flatnonzero(new)
        size = np.diff(np.append(begin, len(h)))
        for c in range(2, most + 1):
            member = ids[begin[size == c][:, None] + np.arange(c)]  # rising
            a, b = np.triu_indices(c, 1)
            yield member[:, a].ravel(), member[:, b].ravel()

    def dealt(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        a, b = _distinct_pairs(*(np.concatenate(c) for c in zip(*held)))
        a, b = a[a != NO_ID], b[a != NO_ID]  # the smallest number: it is never the larger id
        mixed = a.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return _dealt((mixed >> np.uint64(64 - (GRAM_BUCKETS - 1).bit_length())).astype(np.uint16), a, b)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for h, g, ids in _by_bucket(batches):
            for found in pairs(np.frombuffer(h, dtype=np.uint64), np.frombuffer(g, dtype=np.uint32), np.frombuffer(ids, dtype=np.int64)):
                held.append(found)
                size += len(found[0])
            if size >= PAIRS:
                yield dealt(held)
                held, size = [], 0
        if held:
            yield dealt(held)

    return run


def _both_ways(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Distinct edges (src, dst) in both directions from dealt pairs."""
    for first, second, _ in _by_bucket(batches):
        a, b = _distinct_pairs(np.frombuffer(first, dtype=np.int64), np.frombuffer(second, dtype=np.int64))
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([a, b])), pa.array(np.concatenate([b, a]))], names=["src", "dst"])


def shingle_documents(spark: SparkSession, sf_dir: str, buckets: int = 64, label: str = "lang", noise: float = 0.0, seed: int = 7, n: int = 3, most: int = 10) -> Graph:
    """Documents that share a word n-gram held by 2 to ``most`` documents; label: language or quality."""
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.coalesce("text", F.lit("")).alias("text"), "lang")
    ship(spark)
    # grams travel as 96-bit digests, many to a row of one bucket; a bucket holds every document of its grams
    grams = spread(docs).select(F.col("id").cast("long"), "text").mapInArrow(_grams(n), DEALT)
    # so do pairs: a bucket holds all pairs of its smaller documents
    halves = grams.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_sharing(most), DEALT)
    pairs = halves.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_both_ways, "src long, dst long")
    if label == "lang":
        marks = docs.select("id", F.pmod(F.crc32(F.encode("lang", "UTF-8")), F.lit(1 << 30)).alias("h"))
        names = docs.select("lang").filter("lang is not null").distinct().select("lang", (F.row_number().over(Window.orderBy("lang")) - 1).alias("label"))
        marks = docs.select("id", "lang").join(F.broadcast(names), "lang", "left").select("id", "label")
    else:
        marks = load(spark, sf_dir, "labels").groupBy(F.col("doc_id").alias("id")).agg(F.max(label).alias("label"))
    feats = _bigram_nodes(docs, buckets, noise, seed)
    zero = F.array_repeat(F.lit(0.0), buckets)
    nodes = docs.select("id").join(feats, "id", "left").join(marks, "id", "left").select("id", F.coalesce("feat", zero).alias("feat"), "label")
    return Graph(as_nodes(nodes), as_edges(pairs))


def knn_embeddings(spark: SparkSession, sf_dir: str, k: int = 10, block: int = 2048) -> Graph:
    """Each vector's ``k`` nearest others by dot product; exact, block of queries against block of rows.

    A block is one row that holds its vectors, so the pairs of blocks (not of
    vectors) are joined and each is one matrix product; the work is quadratic by
    definition of the exact graph.
    """
    import pandas as pd

    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding", "label")
    blocks = e.groupBy(F.floor(F.col("id") / block).alias("b")).agg(F.sort_array(F.collect_list(F.struct("id", "embedding"))).alias("rows"))
    pairs = blocks.select(F.col("b").alias("qb"), F.col("rows").alias("q")).join(blocks.select(F.col("b").alias("rb"), F.col("rows").alias("r")), F.col("qb").isNotNull() & F.col("rb").isNotNull())

    def nearest(batches):
        for pdf in batches:
            for q, r in zip(pdf.q, pdf.r):
                qi, ri = np.array([x["id"] for x in q]), np.array([x["id"] for x in r])
                score = np.stack([x["embedding"] for x in q]) @ np.stack([x["embedding"] for x in r]).T
                score[qi[:, None] == ri[None, :]] = -np.inf
                top = np.argsort(-score, axis=1, kind="stable")[:, :k]
                keep = np.take_along_axis(score, top, axis=1)
                yield pd.DataFrame({"dst": np.repeat(qi, top.shape[1]), "src": ri[top].ravel(), "score": keep.ravel().astype(float)}).query("score > -1e30")

    cand = pairs.mapInPandas(nearest, "dst long, src long, score double")
    best = cand.withColumn("r", F.row_number().over(Window.partitionBy("dst").orderBy(F.desc("score"), "src"))).filter(F.col("r") <= k)
    return Graph(as_nodes(e.select("id", F.col("embedding").alias("feat"), "label")), as_edges(best))


def page_links(spark: SparkSession, sf_dir: str, buckets: int = 16) -> Graph:
    """Pages and the paths they link to, both directions; label: the page's language attribute."""
    pages = load(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.coalesce("html", F.lit("")).alias("text"))
    hrefs = pages.select("id", F.explode(F.array_distinct(F.regexp_extract_all("text", F.lit('href="([^"]*)"'), F.lit(1)))).alias("target"))
    # identifiers in sorted order need one rank over the distinct targets; a hash stands in for it at scale
    targets = hrefs.select("target").distinct().select("target", (F.dense_rank().over(Window.orderBy("target")) - 1 + SECOND).cast("long").alias("tid"))
    links = hrefs.join(targets, "target").select(F.col("id").alias("src"), F.col("tid").alias("dst"))
    both = links.unionByName(links.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    lang = F.regexp_extract("text", 'lang="([a-z]+)"', 1)
    label = F.when(lang == "en", 0).when(lang == "fr", 1).when(lang == "de", 2).when(lang == "es", 3)
    page_nodes = _bigram_nodes(pages, buckets, 0.0, 0).join(pages.select("id", label.alias("label")), "id")
    target_nodes = targets.select(F.col("tid").alias("id"), F.array_repeat(F.lit(0.0), buckets).alias("feat"), F.lit(None).cast("int").alias("label"))
    return Graph(as_nodes(page_nodes.unionByName(target_nodes)), as_edges(both))


def succession(events: DataFrame, bin_seconds: int = 3600) -> DataFrame:
    """(u, v) for every event of v that directly follows one of u, in order of (ts, event_id).

    Order is global, but no task sees all events: neighbours are found inside
    time bins, and the first event of a bin meets the last of the bin before it
    through a table with a row per bin.
    """
    e = events.select(F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / (bin_seconds * 1_000_000)).alias("bin"), "ts", "event_id", "user_id")
    order = Window.partitionBy("bin").orderBy("ts", "event_id")
    inner = e.withColumn("u", F.lag("user_id").over(order)).filter("u is not null").select("u", F.col("user_id").alias("v"))
    key = F.struct("ts", "event_id", "user_id")
    ends = e.groupBy("bin").agg(F.min(key).alias("first"), F.max(key).alias("last"))
    steps = ends.withColumn("u", F.lag(F.col("last.user_id")).over(Window.orderBy("bin")))
    return inner.unionByName(steps.filter("u is not null").select("u", F.col("first.user_id").alias("v")))


def user_succession(spark: SparkSession, sf_dir: str, min_count: int = 2) -> Graph:
    """Users whose events follow each other at least ``min_count`` times."""
    ev = load(spark, sf_dir, "events")
    pairs = succession(ev).filter("u <> v").groupBy("u", "v").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") >= min_count)
    kinds = ("view", "click", "purchase", "error", "signup", "login", "logout")
    agg = ev.groupBy(F.col("user_id").alias("id")).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("m"), *[F.sum((F.col("event_type") == t).cast("double")).alias(t) for t in kinds])
    feat = F.array(F.log1p("n"), F.coalesce("m", F.lit(0.0)) / 100.0, *[F.col(t) / F.col("n") for t in kinds])
    return Graph(as_nodes(agg.select("id", feat.alias("feat"), F.pmod("id", F.lit(4)).alias("label"))), as_edges(pairs.select(F.col("u").alias("src"), F.col("v").alias("dst"))))


def conversation_turns(spark: SparkSession, sf_dir: str, buckets: int = 8) -> Graph:
    """Each turn points to the next one of its conversation; node id = conversation * 1000 + turn."""
    c = load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.coalesce("text", F.lit("")).alias("text"), "role").dropDuplicates(["id"])
    edges = c.select(F.col("id").alias("src")).join(c.select((F.col("id") - 1).alias("src"), F.col("id").alias("dst")), "src").filter("dst % 1000 <> 0")
    label = F.when(F.col("role") == "user", 0).when(F.col("role") == "assistant", 1).otherwise(2)
    return Graph(as_nodes(_bigram_nodes(c, buckets, 0.0, 0).join(c.select("id", label.alias("label")), "id")), as_edges(edges))


def customer_part(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers and the parts they ordered, both directions."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    pairs = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") + SECOND).alias("src"), F.col("l_partkey").alias("dst")).distinct()
    back = pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    c = load(spark, sf_dir, "customer")
    cust = c.select((F.col("c_custkey") + SECOND).alias("id"), F.array(F.lit(0.0), F.col("c_nationkey") / 25.0, F.col("c_acctbal") / 10000.0, *[F.lit(0.0)] * 5).alias("feat"), F.lit(None).cast("int").alias("label"))
    return Graph(as_nodes(_part_nodes(spark, sf_dir).unionByName(cust)), as_edges(pairs.unionByName(back)))


BUILDERS = {
    "copurchase": copurchase_parts,
    "part_supplier": part_supplier,
    "documents": shingle_documents,
    "knn": knn_embeddings,
    "links": page_links,
    "succession": user_succession,
    "turns": conversation_turns,
    "customer_part": customer_part,
}
