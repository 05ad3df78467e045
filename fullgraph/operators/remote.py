"""Local and remote edges, strategies to ship a remote graph, and per-edge routing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PAIR = ["sp", "dp"]


def located(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """Edges with the parts of both ends: sp, dp, src, dst, w."""
    at = lambda end, name: parts.select(F.col("id").alias(end), F.col("part").alias(name))
    return edges.join(at("src", "sp"), "src").join(at("dst", "dp"), "dst").select("sp", "dp", "src", "dst", "w")


def located_by_mod(edges: DataFrame, parts: int) -> DataFrame:
    """The same for the partition ``id mod parts``: no join at all."""
    of = lambda c: F.pmod(F.col(c), F.lit(parts)).cast("int")
    return edges.select(of("src").alias("sp"), of("dst").alias("dp"), "src", "dst", "w")


def split(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(local, remote) of located edges."""
    return edges.filter("sp = dp"), edges.filter("sp <> dp")


def boundary(remote: DataFrame) -> DataFrame:
    """Sources whose vectors a part needs: (src, sp, dp), each once."""
    return remote.select("src", "sp", "dp").distinct()


def inner(nodes: DataFrame, remote: DataFrame) -> DataFrame:
    """Nodes that need nothing from another part."""
    return nodes.join(remote.select(F.col("dst").alias("id")), "id", "left_anti")


def volumes(remote: DataFrame) -> DataFrame:
    """Per pair of parts: edges, pre (distinct destinations), post (distinct sources), best of the two."""
    # two map-side distincts and one aggregate; a count of two distinct columns would expand every row
    by_dst = remote.groupBy("sp", "dp", "dst").agg(F.count(F.lit(1)).alias("e")).groupBy("sp", "dp").agg(F.sum("e").alias("edges"), F.count(F.lit(1)).alias("pre"))
    by_src = boundary(remote).groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("post"))
    return by_dst.join(by_src, PAIR).select("sp", "dp", "edges", "pre", "post", F.least("pre", "post").alias("best_of_two"))


def route_fixed(remote: DataFrame, strategy: str) -> DataFrame:
    """Routes that need no cover: ``edge``, ``pre``, ``post`` or ``best_of_two`` (ties go to post)."""
    if strategy in ("edge", "pre", "post"):
        return remote.withColumn("route", F.lit(strategy))
    if strategy != "best_of_two":
        raise ValueError(strategy)
    v = volumes(remote).select("sp", "dp", F.when(F.col("post") <= F.col("pre"), "post").otherwise("pre").alias("route"))
    return remote.join(v, PAIR)


def route(remote: DataFrame, cover: DataFrame) -> DataFrame:
    """``post`` where the cover holds an edge's source, else ``pre``."""
    chosen = cover.filter("side = 'src'").select("sp", "dp", F.col("id").alias("src"), F.lit("post").alias("_r"))
    return remote.join(chosen, ["sp", "dp", "src"], "left").select("sp", "dp", "src", "dst", "w", F.coalesce("_r", F.lit("pre")).alias("route"))


def shipped(routed: DataFrame) -> DataFrame:
    """Vectors that cross per pair: distinct post sources plus distinct pre destinations, or every edge of route ``edge``."""
    key = F.when(F.col("route") == "post", F.col("src")).otherwise(F.col("dst"))
    second = F.when(F.col("route") == "edge", F.col("src"))
    return routed.select("sp", "dp", "route", key.alias("key"), second.alias("second")).distinct().groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("vectors"))


def plan(remote: DataFrame, strategy: str = "hybrid", **options) -> DataFrame:
    """Routed remote edges under a strategy: edge, pre, post, best_of_two, hybrid or approx_cover.

    ``edge`` sends a vector per cut edge.  It is the baseline that no reduction is
    taken from, and materializes every edge's message: not a plan for large graphs.
    """
    if strategy == "hybrid":
        from .cover import routed_by_cover

        return routed_by_cover(remote, **options)
    if strategy == "approx_cover":
        from .cover import greedy_cover

        return route(remote, greedy_cover(remote, **options))
    return route_fixed(remote, strategy)
