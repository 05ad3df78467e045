"""Connected components of an undirected edge table, by alternating star contractions.

Each round re-hangs every neighbour above (large star) and below (small star) a
node on the smallest node around it.  Both are an aggregate that combines on the
map side and a join with one row per node on one side, so a node that touches a
third of all edges does not gather them in one task.  The number of rounds grows
with the logarithm of the number of nodes.  Rounds end with a table in the shared
folder, in a file per ``EDGES`` edges; only a count and a checksum of the edges reach
the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import stored

MAX_ROUNDS = 60
#: Edges of a task, and of a file, between two rounds.
EDGES = 200_000


def _mark(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("a", "b")).alias("x")).first()
    return r.n, r.x or 0


def connected(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(node, component) for every node of ``edges`` (columns a, b); component is the smallest node."""
    now = stored(spark, edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    mark = _mark(now)
    few = lambda rows: rows.coalesce(max(1, -(-mark[0] // EDGES)))  # noqa: E731  no round has more edges than the one before, but for one per node
    for _ in range(MAX_ROUNDS):
        if not mark[0]:
            break
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min(F.least("a", "b")).alias("m"))
        large = both.filter("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        small = down.join(least, "a").select(F.greatest("b", "m").alias("a"), F.least("b", "m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        now = stored(spark, few(small.filter("a <> b").distinct()), "edges")
        before, mark = mark, _mark(now)
        if mark == before:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("b").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return few(now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots))
