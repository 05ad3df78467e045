"""Node partitioning: naive controls, balanced label propagation, multilevel minimum cut."""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut
from . import quantiles

MAX_DRIVER_EDGES = 1_000_000
MAX_DRIVER_NODES = 1_000_000


def by_hash(nodes: DataFrame, parts: int) -> DataFrame:
    return nodes.select("id", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int").alias("part"))


def by_mod(nodes: DataFrame, parts: int) -> DataFrame:
    return nodes.select("id", F.pmod("id", F.lit(parts)).cast("int").alias("part"))


def by_range(nodes: DataFrame, parts: int) -> DataFrame:
    """Equal slices of the identifiers in order (exact quantiles, no sort in one task)."""
    cuts = quantiles.exact(nodes, F.col("id"), [i / parts for i in range(1, parts)]) if parts > 1 else []
    part = F.lit(0)
    for c in cuts:
        part = part + F.when(F.col("id") > c, 1).otherwise(0)
    return nodes.select("id", part.alias("part"))


def by_column(nodes: DataFrame, column: str) -> DataFrame:
    return nodes.select("id", F.col(column).cast("int").alias("part"))


def node_weights(nodes: DataFrame, edges: DataFrame, train_weight: float = 1.0) -> DataFrame:
    """In-degree plus ``train_weight`` for training nodes."""
    d = edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("d"))
    return nodes.join(d, "id", "left").select("id", (F.coalesce("d", F.lit(0)) + F.when(F.col("split") == "train", F.lit(train_weight)).otherwise(0.0)).alias("weight"))


def _affinity(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """(id, part, gain): weight of a node's edges into each part."""
    both = edges.select("src", "dst", "w").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return both.join(parts.select(F.col("id").alias("dst"), "part"), "dst").groupBy(F.col("src").alias("id"), "part").agg(F.sum("w").alias("gain"))


def propagate(nodes: DataFrame, edges: DataFrame, parts: int, rounds: int = 4, imbalance: float = 0.1, weights: DataFrame | None = None, start: DataFrame | None = None) -> DataFrame:
    """Balanced label propagation: nodes move to the part most of their neighbours are in, while it has room.

    Candidates for a part are admitted by a hash of their gain rank: a part's
    free room over its candidates' weight is the chance of a move, so no part's
    candidates are sorted in one task.
    """
    spark = nodes.sparkSession
    w = cut(spark, (weights or nodes.select("id", F.lit(1.0).alias("weight"))).select("id", F.col("weight").cast("double").alias("weight")), "weights")
    now = cut(spark, start if start is not None else by_hash(nodes, parts), "parts")
    total = w.agg(F.sum("weight")).first()[0] or 0.0
    room = (1 + imbalance) * total / parts
    for r in range(rounds):
        gains = _affinity(edges, now)
        best = gains.groupBy("id").agg(F.max_by("part", F.struct("gain", -F.col("part"))).alias("to"), F.max("gain").alias("top"))
        stay = gains.join(now, ["id", "part"], "right").select("id", "part", F.coalesce("gain", F.lit(0.0)).alias("here"))
        move = stay.join(best, "id").filter((F.col("top") > F.col("here")) & (F.col("to") != F.col("part"))).join(w, "id")
        load = now.join(w, "id").groupBy("part").agg(F.sum("weight").alias("load"))
        asked = move.groupBy(F.col("to").alias("part")).agg(F.sum("weight").alias("asked"))
        # rows of one number of parts: small, so the chance table is broadcast
        chance = load.join(asked, "part", "left").select(F.col("part").alias("to"), F.when(F.col("asked") > 0, (F.lit(room) - F.col("load")) / F.col("asked")).otherwise(1.0).alias("chance"))
        go = move.join(F.broadcast(chance), "to", "left").filter(F.pmod(F.xxhash64("id", F.lit(r)), F.lit(1000)) < F.coalesce("chance", F.lit(1.0)) * 500).select("id", F.col("to").cast("int").alias("to"))
        now = cut(spark, now.join(go, "id", "left").select("id", F.coalesce("to", "part").alias("part")), "parts")
    return now


def coarsen(edges: DataFrame, weights: DataFrame, seed: int = 0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(map id to coarse id, coarse edges, coarse weights): heavy-edge matching in one handshake round."""
    both = edges.select("src", "dst", "w").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    tie = F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst"), F.lit(seed))
    pick = both.filter("src <> dst").groupBy("src").agg(F.max_by("dst", F.struct("w", tie.alias("t"))).alias("mate"))
    mutual = pick.join(pick.select(F.col("src").alias("mate"), F.col("mate").alias("back")), "mate").filter("back = src")
    to = weights.select("id").join(mutual.select(F.col("src").alias("id"), F.least("src", "mate").alias("coarse")), "id", "left").select("id", F.coalesce("coarse", "id").alias("coarse"))
    to = cut(edges.sparkSession, to, "coarse-map")
    at = lambda end: to.select(F.col("id").alias(end), F.col("coarse").alias(f"c_{end}"))
    small = edges.join(at("src"), "src").join(at("dst"), "dst").filter("c_src <> c_dst").groupBy(F.least("c_src", "c_dst").alias("src"), F.greatest("c_src", "c_dst").alias("dst")).agg(F.sum("w").alias("w"))
    return to, small, weights.join(to, "id").groupBy(F.col("coarse").alias("id")).agg(F.sum("weight").alias("weight"))


def grow_parts(n: int, u: np.ndarray, v: np.ndarray, w: np.ndarray, weight: np.ndarray, parts: int, imbalance: float) -> np.ndarray:
    """Parts of a graph in memory: greedy growth by attachment, then passes of single moves."""
    order = np.argsort(np.concatenate([u, v]), kind="stable")
    head, tail, ww = np.concatenate([u, v])[order], np.concatenate([v, u])[order], np.concatenate([w, w])[order]
    begin = np.searchsorted(head, np.arange(n + 1))
    part = np.full(n, -1)
    room = weight.sum() / parts
    free = iter(np.argsort(-np.diff(begin), kind="stable").tolist())
    for p in range(parts):
        load, gain, heap = 0.0, {}, []
        while load < room or p == parts - 1:
            while heap and (part[heap[0][1]] >= 0 or -heap[0][0] != gain[heap[0][1]]):
                heapq.heappop(heap)
            x = heapq.heappop(heap)[1] if heap else next((i for i in free if part[i] < 0), None)
            if x is None:
                break
            part[x], load = p, load + weight[x]
            for k in range(begin[x], begin[x + 1]):
                y = tail[k]
                if part[y] < 0:
                    gain[y] = gain.get(y, 0.0) + ww[k]
                    heapq.heappush(heap, (-gain[y], int(y)))
    limit = (1 + imbalance) * room
    load = np.bincount(part, weights=weight, minlength=parts)
    for _ in range(8):
        moved = 0
        for x in range(n):
            to = np.bincount(part[tail[begin[x] : begin[x + 1]]], weights=ww[begin[x] : begin[x + 1]], minlength=parts)
            best = int(to.argmax())
            if to[best] > to[part[x]] and load[best] + weight[x] <= limit:
                load[part[x]] -= weight[x]
                load[best] += weight[x]
                part[x] = best
                moved += 1
        if not moved:
            break
    return part


def multilevel(nodes: DataFrame, edges: DataFrame, parts: int, imbalance: float = 0.05, train_weight: float = 1.0, levels: int = 12, max_driver_edges: int = MAX_DRIVER_EDGES, max_driver_nodes: int = MAX_DRIVER_NODES, target: int = 0) -> DataFrame:
    """Minimum-cut partition: coarsen by matching, cut the small graph on the driver, refine on the way back.

    The driver takes the coarse graph only once it has at most ``max_driver_edges`` edges and
    ``max_driver_nodes`` nodes with an edge.  Nodes without one never match and never pay for
    where they are: they are dealt by hash where they are, whatever their number.  A coarse graph
    that stays above the bounds after ``levels`` levels is partitioned by balanced propagation.
    """
    spark = nodes.sparkSession
    weights = cut(spark, node_weights(nodes, edges, train_weight).withColumn("weight", F.col("weight") + 1.0), "weights")
    e = edges.filter("src <> dst").groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.sum("w").alias("w"))
    e = cut(spark, e, "edges")
    ends = e.select(F.col("src").alias("id")).unionByName(e.select(F.col("dst").alias("id"))).distinct()
    alone = by_hash(weights.join(ends, "id", "left_anti"), parts)
    weights = cut(spark, weights.join(ends, "id", "left_semi"), "weights")
    maps, stack = [], [(e, weights)]
    goal = target or 40 * parts
    for i in range(levels):
        n = weights.count()
        fits = n <= max_driver_nodes and e.count() <= max_driver_edges
        if n <= goal and fits:
            break
        to, e, weights = coarsen(e, weights, i)
        e, weights = cut(spark, e, "edges"), cut(spark, weights, "weights")
        maps.append(to)
        stack.append((e, weights))
        if weights.count() > 0.95 * n and weights.count() <= max_driver_nodes and e.count() <= max_driver_edges:
            break
    if e.count() > max_driver_edges or weights.count() > max_driver_nodes:
        now = propagate(weights, e, parts, 6, imbalance, weights)
    else:
        w = weights.orderBy("id").toPandas()  # at most max_driver_nodes rows
        ids = w["id"].to_numpy()
        pairs = e.toPandas()
        at = lambda c: np.searchsorted(ids, pairs[c].to_numpy())
        got = grow_parts(len(ids), at("src"), at("dst"), pairs["w"].to_numpy(dtype=float), w["weight"].to_numpy(dtype=float), parts, imbalance)
        now = spark.createDataFrame([(int(i), int(p)) for i, p in zip(ids, got)], "id long, part int")
    for to, (fine_e, fine_w) in zip(reversed(maps), reversed(stack[:-1])):
        fine = to.join(now.withColumnRenamed("id", "coarse"), "coarse").select("id", "part")
        now = propagate(fine_w, fine_e, parts, 1, imbalance, fine_w, fine)
    return now.select("id", "part").unionByName(alone)
