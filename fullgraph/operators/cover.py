"""Minimum vertex covers of the bipartite cut graphs, pair of parts by pair of parts.

The cover is computed on edge identifiers only.  Pairs are dealt by (sp, dp) and
each is solved by maximum matching and the alternating reach of the unmatched
sources: sources outside the reach and destinations inside it are the cover.
That cover does not depend on which maximum matching was found, so routes are
reproducible.  The matching starts from leaves and free pairs, then phases grow
trees from all unmatched sources at once; every step is a few passes over arrays.

A pair with more than ``max_pair_edges`` edges is first cut into connected
components by a distributed pass.  A component that is still larger does not fit
the task: that is an error, unless the caller asks for an approximation
(``approximate=True``), which is the cover of a greedy matching for those
components, at most twice the minimum.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut, ship
from .remote import PAIR

MAX_PAIR_EDGES = 4_000_000


def _edges_of(front: np.ndarray, begin: np.ndarray, to: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(left, right) of every edge of the left vertices ``front``; ``begin`` and ``to`` list edges by left vertex."""
    n = begin[front + 1] - begin[front]
    at = np.repeat(begin[front], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    return np.repeat(front, n), to[at]


def _start(n_left: int, n_right: int, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A matching to begin with: vertices with one open edge take it while there are many, then whoever is free."""
    mate_l, mate_r = np.full(n_left, -1), np.full(n_right, -1)
    while len(left):
        before = len(left)
        deg_l, deg_r = np.bincount(left, minlength=n_left), np.bincount(right, minlength=n_right)
        leaf = (deg_l[left] == 1) | (deg_r[right] == 1)
        u, v = (left[leaf], right[leaf]) if leaf.sum() * 100 >= before else (left, right)
        # each left vertex names its first open neighbour, each right vertex takes one that named it
        u, at = np.unique(u, return_index=True)
        v, at = np.unique(v[at], return_index=True)
        mate_l[u[at]], mate_r[v] = v, u[at]
        rest = (mate_l[left] < 0) & (mate_r[right] < 0)
        left, right = left[rest], right[rest]
    return mate_l, mate_r


def _grow(begin: np.ndarray, to: np.ndarray, mate_l: np.ndarray, mate_r: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Alternating trees from all free left vertices at once, level by level.

    Returns (ends of augmenting paths, parent of every reached right vertex, is each left vertex reached).
    Trees share no vertex, a tree stops at its first end, and without an end the reach is complete.
    """
    root = np.where(mate_l < 0, np.arange(len(mate_l)), -1)
    parent = np.full(len(mate_r), -1)
    done = np.zeros(len(mate_l), dtype=bool)
    ends = []
    front = np.flatnonzero(mate_l < 0)
    while len(front):
        u, v = _edges_of(front, begin, to)
        new = parent[v] < 0
        v, at = np.unique(v[new], return_index=True)
        u = u[new][at]
        parent[v] = u
        free = mate_r[v] < 0
        tree, first = np.unique(root[u[free]], return_index=True)
        ends.append(v[free][first])
        done[tree] = True
        on = ~free & ~done[root[u]]
        front = mate_r[v[on]]
        root[front] = root[u[on]]
    return (np.concatenate(ends) if ends else np.zeros(0, dtype=np.int64)), parent, root >= 0


def max_matching(n_left: int, n_right: int, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """A maximum matching of the edges (left, right) and what the unmatched left vertices reach by alternating paths.

    (partner of each left vertex, of each right vertex, is each left reached, is each right reached); -1 is no partner.
    """
    order = np.argsort(left, kind="stable")
    begin, to = np.searchsorted(left[order], np.arange(n_left + 1)), right[order]
    mate_l, mate_r = _start(n_left, n_right, left, right)
    while True:
        v, parent, reached = _grow(begin, to, mate_l, mate_r)
        if not len(v):
            return mate_l, mate_r, reached, parent >= 0
        while len(v):  # flip all paths, an edge of each at a time
            u = parent[v]
            before = mate_l[u]
            mate_l[u], mate_r[v] = v, u
            v = before[before >= 0]


def konig_cover(left: np.ndarray, right: np.ndarray, side: str = "src") -> tuple[np.ndarray, np.ndarray, int]:
    """(is each left vertex covered, is each right vertex covered, size of the matching).

    ``side`` names the side whose unmatched vertices the reach starts from; both give a cover of one size.
    """
    if side == "dst":
        b, a, size = konig_cover(right, left, "src")
        return a, b, size
    mate_l, _, reach_l, reach_r = max_matching(int(left.max()) + 1, int(right.max()) + 1, left, right)
    return ~reach_l, reach_r, int((mate_l >= 0).sum())


def groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[tuple[tuple, pa.Table]]:
    """Runs of rows with equal first ``keys`` columns, over batches sorted by them."""
    held: list[pa.RecordBatch] = []
    key = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [np.asarray(batch.column(i)) for i in range(keys)]
        change = np.zeros(batch.num_rows, dtype=bool)
        for c in cols:
            change[1:] |= c[1:] != c[:-1]
        edge = [0, *np.flatnonzero(change).tolist(), batch.num_rows]
        for lo, hi in zip(edge[:-1], edge[1:]):
            now = tuple(int(c[lo]) for c in cols)
            if held and now != key:
                yield key, pa.Table.from_batches(held)
                held = []
            key = now
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield key, pa.Table.from_batches(held)


def _route_pairs(side: str, limit: int, approximate: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (sp, dp, _), t in groups(batches, 3):
            u = np.unique(t["src"].to_numpy(), return_inverse=True)[1]
            v = np.unique(t["dst"].to_numpy(), return_inverse=True)[1]
            if len(u) > limit:
                if not approximate:
                    raise ValueError(f"parts {sp} to {dp}: a component of {len(u)} cut edges, more than {limit}; use more parts, a larger max_pair_edges, or approximate=True")
                covered = greedy_arrays(u, v)[0]
            else:
                covered = konig_cover(u, v, side)[0]
            routes = np.where(covered[u], "post", "pre")
            yield pa.RecordBatch.from_arrays([t[c].combine_chunks() for c in ("sp", "dp", "src", "dst", "w")] + [pa.array(routes)], names=["sp", "dp", "src", "dst", "w", "route"])

    return run


def greedy_arrays(left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both ends of a maximal matching: a cover of at most twice the minimum."""
    mate_l, mate_r = _start(int(left.max()) + 1, int(right.max()) + 1, left, right)
    return mate_l >= 0, mate_r >= 0


def _with_component(remote: DataFrame, max_pair_edges: int) -> DataFrame:
    """Add ``comp``: 0, or the component inside a pair that is too large for one task."""
    spark = remote.sparkSession
    large = remote.groupBy(*PAIR).agg(F.count(F.lit(1)).alias("e")).filter(F.col("e") > max_pair_edges).select(*PAIR)
    large = cut(spark, large, "large-pairs")
    if large.isEmpty():
        return remote.withColumn("comp", F.lit(0).cast("long"))
    rest = remote.join(large, PAIR, "left_anti").withColumn("comp", F.lit(0).cast("long"))
    big = remote.join(large, PAIR, "left_semi")
    return rest.unionByName(components(big).withColumnRenamed("component", "comp"))


def routed_by_cover(remote: DataFrame, side: str = "src", max_pair_edges: int = MAX_PAIR_EDGES, approximate: bool = False) -> DataFrame:
    """Remote edges with their route under the minimum cover; the cover and the route come from one pass."""
    ship(remote.sparkSession)
    rows = _with_component(remote, max_pair_edges).select("sp", "dp", "comp", "src", "dst", "w")
    dealt = rows.repartition("sp", "dp", "comp").sortWithinPartitions("sp", "dp", "comp")
    return dealt.mapInArrow(_route_pairs(side, max_pair_edges, approximate), "sp int, dp int, src long, dst long, w double, route string")


def cover_of(routed: DataFrame) -> DataFrame:
    """(sp, dp, side, id): the cover that a routing stands for."""
    post = routed.filter("route = 'post'").select("sp", "dp", F.lit("src").alias("side"), F.col("src").alias("id"))
    pre = routed.filter("route = 'pre'").select("sp", "dp", F.lit("dst").alias("side"), F.col("dst").alias("id"))
    return post.unionByName(pre).distinct()


def minimum_cover(remote: DataFrame, side: str = "src", max_pair_edges: int = MAX_PAIR_EDGES, approximate: bool = False) -> DataFrame:
    return cover_of(routed_by_cover(remote, side, max_pair_edges, approximate))


def matching_sizes(remote: DataFrame) -> DataFrame:
    """(sp, dp, matched): size of a maximum matching of every pair."""
    ship(remote.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (sp, dp), t in groups(batches, 2):
            u = np.unique(t["src"].to_numpy(), return_inverse=True)[1]
            v = np.unique(t["dst"].to_numpy(), return_inverse=True)[1]
            size = int((max_matching(int(u.max()) + 1, int(v.max()) + 1, u, v)[0] >= 0).sum())
            yield pa.RecordBatch.from_arrays([pa.array([sp], pa.int32()), pa.array([dp], pa.int32()), pa.array([size], pa.int64())], names=["sp", "dp", "matched"])

    dealt = remote.select("sp", "dp", "src", "dst").repartition("sp", "dp").sortWithinPartitions("sp", "dp")
    return dealt.mapInArrow(run, "sp int, dp int, matched long")


def components(remote: DataFrame, rounds: int = 1000) -> DataFrame:
    """Remote edges with ``component``: the smallest source of the edge's component within its pair.

    Labels spread from sources to destinations and back; after each exchange a
    source also takes the label of the source its label names (pointer jumping).
    Labels that do not settle within ``rounds`` are an error.
    """
    spark = remote.sparkSession
    edges = remote.select("sp", "dp", "src", "dst")
    label = cut(spark, edges.select("sp", "dp", "src").distinct().withColumn("c", F.col("src")), "labels")
    before = None
    for _ in range(rounds):
        at_dst = edges.join(label, ["sp", "dp", "src"]).groupBy("sp", "dp", "dst").agg(F.min("c").alias("c"))
        at_src = edges.join(at_dst, ["sp", "dp", "dst"]).groupBy("sp", "dp", "src").agg(F.min("c").alias("c"))
        up = at_src.select("sp", "dp", F.col("src").alias("c"), F.col("c").alias("cc"))
        label = cut(spark, at_src.join(up, ["sp", "dp", "c"], "left").select("sp", "dp", "src", F.coalesce("cc", "c").alias("c")), "labels")
        now = label.agg(F.sum(F.col("c").cast("decimal(38,0)"))).first()[0]
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"labels still change after {rounds} rounds")
    return remote.join(label.withColumnRenamed("c", "component"), ["sp", "dp", "src"]).select("sp", "dp", "src", "dst", "w", "component")


def reduce_leaves(remote: DataFrame, rounds: int = 2) -> tuple[DataFrame, DataFrame]:
    """(what is left, cover so far): the neighbour of a vertex with one edge enters a minimum cover.

    Destinations with one edge put their source into the cover, then sources with one edge
    their destination; covered edges leave, and the sizes add up to the minimum.
    """
    spark = remote.sparkSession
    left, chosen = remote, None
    for _ in range(rounds):
        for leaf, hub, side in (("dst", "src", "src"), ("src", "dst", "dst")):
            one = left.groupBy("sp", "dp", leaf).agg(F.count(F.lit(1)).alias("d"), F.first(hub).alias(hub)).filter("d = 1")
            hubs = cut(spark, one.select("sp", "dp", hub).distinct(), "hubs")
            left = cut(spark, left.join(hubs, ["sp", "dp", hub], "left_anti").select("sp", "dp", "src", "dst", "w"), "left")
            picked = hubs.select("sp", "dp", F.lit(side).alias("side"), F.col(hub).alias("id"))
            chosen = picked if chosen is None else chosen.unionByName(picked)
    return left, chosen


def greedy_cover(remote: DataFrame, rounds: int = 50) -> DataFrame:
    """Cover from a maximal matching found in distributed rounds: at most twice the minimum.

    In a round every source names one free neighbour and every destination takes
    one of those that named it; both ends of each agreement enter the cover.
    """
    spark = remote.sparkSession
    left, chosen = remote.select("sp", "dp", "src", "dst"), None
    for i in range(rounds):
        # the order in which a source names its neighbours changes with the round
        rank = F.struct(F.xxhash64("src", "dst", F.lit(i)).alias("h"), F.col("dst").alias("dst"))
        named = left.groupBy("sp", "dp", "src").agg(F.min(rank)["dst"].alias("dst"))
        taken = cut(spark, named.groupBy("sp", "dp", "dst").agg(F.min("src").alias("src")), "taken")
        left = left.join(taken.select("sp", "dp", "src"), ["sp", "dp", "src"], "left_anti").join(taken.select("sp", "dp", "dst"), ["sp", "dp", "dst"], "left_anti")
        left = cut(spark, left.select("sp", "dp", "src", "dst"), "left")
        both = taken.select("sp", "dp", F.lit("src").alias("side"), F.col("src").alias("id")).unionByName(taken.select("sp", "dp", F.lit("dst").alias("side"), F.col("dst").alias("id")))
        chosen = both if chosen is None else chosen.unionByName(both)
        if left.isEmpty():
            return chosen
    raise RuntimeError("the matching did not become maximal")
