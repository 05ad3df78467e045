"""Operators around the methods: as-of and interval joins, top-k, graph helpers, user functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import cut, ship


def ready(spark: SparkSession) -> None:
    ship(spark)


def asof(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """Left rows with ``matched``: the last right ``value`` of the same key strictly before.

    Both sides are stacked and a running last value is taken: one shuffle, one
    sort, and no product of the two sides.
    """
    both = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(0).alias("_side")).unionByName(right.select(F.col(by), F.col(on), F.col(value).alias("_v"), F.lit(1).alias("_side")), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("matched", F.last("_v", ignorenulls=True).over(w)).filter("_side = 0").drop("_v", "_side")


def within(events: DataFrame, by: str, seconds: int) -> DataFrame:
    """(x, y) of events of one key where y comes after x by at most ``seconds``.

    Time is cut into bins of that length: a partner is in the same bin or the
    next, so the join has an equality on (key, bin).
    """
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    t = events.select(F.col("event_id"), F.col(by), micros.alias("t"), F.floor(micros / (seconds * 1_000_000)).alias("bin"))
    a = t.select(F.col("event_id").alias("x"), by, F.col("t").alias("tx"), F.explode(F.array(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    b = t.select(F.col("event_id").alias("y"), by, F.col("t").alias("ty"), "bin")
    return a.join(b, [by, "bin"]).filter((F.col("ty") > F.col("tx")) & (F.col("ty") <= F.col("tx") + seconds * 1_000_000)).select("x", "y")


def top_k(df: DataFrame, key: str, order: list[Column | str], k: int) -> DataFrame:
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(key).orderBy(*order))).filter(F.col("_r") <= k).drop("_r")


def khop(edges: DataFrame, start: DataFrame, hops: int) -> DataFrame:
    """Nodes within ``hops`` steps of the start."""
    seen = start.select("id")
    for _ in range(hops):
        step = edges.join(seen.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("id"))
        seen = seen.unionByName(step).distinct()
    return seen


def triangles(edges: DataFrame) -> DataFrame:
    """Number of triangles of the undirected graph; wedges start at the end of smaller degree, which bounds them at hubs."""
    u = edges.filter("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    deg = u.select(F.explode(F.array("a", "b")).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("d"))
    at = lambda c: deg.select(F.col("n").alias(c), F.struct("d", "n").alias(f"k{c}"))
    o = u.join(at("a"), "a").join(at("b"), "b").select(F.when(F.col("ka") < F.col("kb"), F.col("a")).otherwise(F.col("b")).alias("lo"), F.when(F.col("ka") < F.col("kb"), F.col("b")).otherwise(F.col("a")).alias("hi"))
    wedge = o.select("lo", F.col("hi").alias("x")).join(o.select("lo", F.col("hi").alias("y")), "lo").filter("x < y")
    closed = wedge.join(u.select(F.col("a").alias("x"), F.col("b").alias("y")), ["x", "y"], "left_semi")
    return closed.agg(F.count(F.lit(1)).alias("triangles"))


def connected(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """(node, component): smallest reachable node, by spreading labels and jumping along them."""
    spark = edges.sparkSession
    both = cut(spark, edges.select("src", "dst").unionByName(edges.select(F.col("dst"), F.col("src"))).distinct(), "both")
    label = cut(spark, both.select(F.col("src").alias("node"), F.col("src").alias("c")).distinct(), "labels")
    before = None
    for _ in range(rounds):
        near = both.join(label.select(F.col("node").alias("dst"), "c"), "dst").groupBy(F.col("src").alias("node")).agg(F.min("c").alias("m"))
        low = label.join(near, "node", "left").select("node", F.least("c", F.coalesce("m", "c")).alias("c"))
        jump = low.join(low.select(F.col("node").alias("c"), F.col("c").alias("cc")), "c", "left").select("node", F.coalesce("cc", "c").alias("c"))
        label = cut(spark, jump, "labels")
        now = label.agg(F.sum(F.col("c").cast("decimal(38,0)"))).first()[0]
        if now == before:
            break
        before = now
    return label.withColumnRenamed("c", "component")


def pagerank(edges: DataFrame, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """(id, rank) after ``rounds`` passes; ranks of nodes without out-edges are not passed on."""
    spark = edges.sparkSession
    out = edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    e = cut(spark, edges.join(out, "src").select("src", "dst", "d"), "ranked-edges")
    nodes = cut(spark, e.select(F.col("src").alias("id")).unionByName(e.select(F.col("dst").alias("id"))).distinct(), "ids")
    rank = nodes.withColumn("rank", F.lit(1.0))
    for i in range(rounds):
        got = e.join(rank.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") / F.col("d")).alias("s"))
        rank = nodes.join(got, "id", "left").select("id", (F.lit(1 - damping) + damping * F.coalesce("s", F.lit(0.0))).alias("rank"))
        if i % 3 == 2:
            rank = cut(spark, rank, "rank")
    return rank


def vector_sum(df: DataFrame) -> DataFrame:
    """(label, v): sums of whole vectors in a grouped Arrow function (no partial sums; a control for the block layout)."""
    ship(df.sparkSession)

    def run(t: pa.Table) -> pa.Table:
        x = np.array(t["embedding"].to_pylist(), dtype=np.float64).sum(axis=0)
        return pa.table({"label": t["label"].slice(0, 1).combine_chunks(), "v": pa.array([x.tolist()], pa.list_(pa.float64()))})

    kind = df.schema["label"].dataType.simpleString()
    return df.groupBy("label").applyInArrow(run, f"label {kind}, v array<double>")


def register_udtf(spark: SparkSession) -> None:
    """``cover_of('u-v,u-v,...')``: a minimum vertex cover of a small bipartite edge list, from SQL."""
    ship(spark)

    @F.udtf(returnType="side string, id bigint")
    class CoverOf:
        def eval(self, edges: str):
            import numpy as np

            from fullgraph.operators.cover import konig_cover

            pairs = [tuple(map(int, e.split("-"))) for e in edges.split(",")]
            us, u = np.unique([a for a, _ in pairs], return_inverse=True)
            vs, v = np.unique([b for _, b in pairs], return_inverse=True)
            a, b, _ = konig_cover(u, v)
            for x in us[a].tolist():
                yield "src", x
            for x in vs[b].tolist():
                yield "dst", x

    spark.udtf.register("cover_of", CoverOf)
