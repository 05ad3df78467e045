"""Neighbour aggregation: scatter-add, sparse-matrix product, and the cover-routed layer.

Vectors travel in the block layout (16 elements), so one group key is (node,
block) and the sums of a block are sixteen plain aggregates in generated code.
The routed layer ships each post source once and each pre destination's partial
sum once per pair of parts; its result equals the product over all edges.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import BLOCK, block_sums, packed

REDUCERS = ("sum", "mean", "max", "min", "count")


def scatter_add(rows: DataFrame, at: str = "idx") -> DataFrame:
    """Rows (idx, blk, v) added up at their index."""
    return rows.groupBy(at, "blk").agg(*block_sums()).select(at, "blk", packed())


def _reduce(joined: DataFrame, keys: list[str], reduce: str, weight: Column | None) -> DataFrame:
    cell = lambda i: F.get(F.col("v"), F.lit(i))
    if reduce in ("max", "min"):
        f = F.max if reduce == "max" else F.min
        return joined.groupBy(*keys).agg(*[f(cell(i)).alias(f"s{i}") for i in range(BLOCK)]).select(*keys, packed())
    if reduce == "count":
        return joined.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias("n"))
    out = joined.groupBy(*keys).agg(*block_sums(weight=weight), F.count(F.lit(1)).alias("n"))
    if reduce == "mean":
        return out.select(*keys, F.transform(packed(), lambda x: x / F.col("n")).alias("v"))
    return out.select(*keys, packed())


BINS = 1024


def work_lanes(edges: DataFrame, lanes: int) -> DataFrame:
    """(dst, lane, salts): destinations dealt so that lanes hold about equal numbers of edges.

    Degrees are summed into ``BINS`` hashed bins, whose prefix sums give the lanes; a
    destination with more edges than a lane's share has its edges dealt over ``salts`` lanes.
    """
    deg = edges.groupBy("dst").agg(F.count(F.lit(1)).alias("d")).withColumn("bin", F.pmod(F.xxhash64("dst"), F.lit(BINS)))
    bins = deg.groupBy("bin").agg(F.sum("d").alias("w"))
    # one row per bin: the ordered window and the table are of that size
    before, whole = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    share = bins.select("bin", F.coalesce(F.sum("w").over(before), F.lit(0)).alias("before"), (F.sum("w").over(whole) / lanes).alias("share"))
    return deg.join(F.broadcast(share), "bin").select("dst", F.least(F.floor(F.col("before") / F.col("share")), F.lit(lanes - 1)).cast("int").alias("lane"), F.ceil(F.col("d") / F.col("share")).cast("int").alias("salts"))


def _balanced(e: DataFrame, feats: DataFrame, weight: Column | None, grid: tuple[int, int]) -> DataFrame:
    pn, pf = grid
    salt = F.pmod(F.xxhash64("src"), F.col("salts")).cast("int")
    dealt = e.join(work_lanes(e, pn), "dst").withColumn("salt", salt).withColumn("lane", F.pmod(F.col("lane") + F.col("salt"), F.lit(pn)))
    j = dealt.join(feats, dealt["src"] == feats["id"]).withColumn("strip", F.pmod("blk", F.lit(pf)))
    cells = j.repartition(pn * pf, "lane", "strip")  # a cell of the grid: a lane of destinations and a strip of features
    part = cells.groupBy("lane", "strip", "dst", "blk", "salts", "salt").agg(*block_sums(weight=weight)).select("dst", "blk", "salts", packed())
    whole = part.filter("salts = 1").select("dst", "blk", "v")
    return whole.unionByName(part.filter("salts > 1").groupBy("dst", "blk").agg(*block_sums()).select("dst", "blk", packed()))


def _clustered(e: DataFrame, feats: DataFrame, weighted: bool, clusters: int) -> DataFrame:
    """Edges clustered and sorted by destination; each cluster gets every source it needs once and adds up runs of rows."""
    import numpy as np
    import pyarrow as pa

    from ..session import ship

    ship(e.sparkSession)
    e = e.withColumn("cluster", F.pmod(F.xxhash64("dst"), F.lit(clusters)).cast("int"))
    need = e.select("cluster", "src").distinct()
    rows = need.join(feats, need["src"] == feats["id"]).select(F.col("cluster").alias("c"), F.col("src").alias("id"), "blk", "v")

    def run(key, edges: pa.Table, vectors: pa.Table) -> pa.Table:
        src, dst, w = (edges[c].to_numpy() for c in ("src", "dst", "w"))
        order = np.lexsort((src, dst))
        src, dst, w = src[order], dst[order], w[order]
        ids, blk = vectors["id"].to_numpy(), vectors["blk"].to_numpy()
        v = np.asarray(vectors["v"].combine_chunks().flatten()).reshape(len(ids), -1) if len(ids) else np.zeros((0, 1))
        out = []
        for b in np.unique(blk):
            mine = np.flatnonzero(blk == b)
            mine = mine[np.argsort(ids[mine])]
            at = np.searchsorted(ids[mine], src)
            has = at < len(mine)
            has[has] = ids[mine[at[has]]] == src[has]
            d, x = dst[has], v[mine[at[has]]]
            if not len(d):
                continue
            first = np.flatnonzero(np.concatenate([[True], d[1:] != d[:-1]]))
            out.append((d[first], np.full(len(first), b), np.add.reduceat(x * w[has, None] if weighted else x, first, axis=0)))
        d, b, s = (np.concatenate(c) for c in zip(*out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros((0, 1)))
        width = s.shape[1]
        return pa.table({"dst": pa.array(d, pa.int64()), "blk": pa.array(b, pa.int32()), "v": pa.ListArray.from_arrays(np.arange(0, s.size + 1, width, dtype=np.int32), pa.array(s.astype(np.float64).ravel()))})

    sums = e.groupBy("cluster").cogroup(rows.groupBy("c")).applyInArrow(run, "dst long, blk int, v array<double>")
    return sums.select("dst", "blk", F.col("v").cast(feats.schema["v"].dataType).alias("v"))


def spmm(edges: DataFrame, feats: DataFrame, reduce: str = "sum", weighted: bool = False, transpose: bool = False, variant: str = "blocked", grid: tuple[int, int] | None = None) -> DataFrame:
    """Aggregate of the in-neighbours' blocks: (dst, blk, v).

    Variants of a sum: ``vanilla`` sends every edge's message to its destination as
    stored and adds it at its index there; ``sorted`` clusters edges by destination and adds up sorted runs in arrays;
    ``blocked`` (default) sums blocks of 16 in generated code before they are exchanged; ``balanced``
    deals a grid of destinations by their number of edges and strips of the features, with hubs split.
    """
    src, dst = ("dst", "src") if transpose else ("src", "dst")
    e = edges.select(F.col(src).alias("src"), F.col(dst).alias("dst"), "w")
    weight = F.col("w") if weighted else None
    cores = e.sparkSession.sparkContext.defaultParallelism
    if reduce == "sum" and variant == "sorted":
        return _clustered(e, feats, weighted, 4 * cores)
    if reduce == "sum" and variant == "balanced":
        return _balanced(e, feats, weight, grid or (2 * cores, 2))
    joined = e.join(feats, e["src"] == feats["id"]).select("src", "dst", "w", "blk", "v")
    if variant == "vanilla":
        joined = joined.repartition("dst")
    return _reduce(joined, ["dst", "blk"], reduce, weight)


def local(local_edges: DataFrame, feats: DataFrame, **options) -> DataFrame:
    """Aggregation over the edges that stay inside their part."""
    return spmm(local_edges, feats, **options)


def each(edge: DataFrame, feats: DataFrame, weighted: bool = False) -> DataFrame:
    """One row per (edge, blk): what crosses where nothing is reduced."""
    j = edge.join(feats, edge["src"] == feats["id"])
    v = F.transform("v", lambda x: x * F.col("w")) if weighted else F.col("v")
    return j.select("sp", "dp", F.lit("partial").alias("kind"), F.col("dst").alias("key"), "blk", v.alias("v"), F.lit(1.0).alias("n"))


def partials(pre: DataFrame, feats: DataFrame, weighted: bool = False) -> DataFrame:
    """One partial sum per (sp, dp, dst, blk), computed at the sender."""
    j = pre.join(feats, pre["src"] == feats["id"])
    out = j.groupBy("sp", "dp", "dst", "blk").agg(*block_sums(weight=F.col("w") if weighted else None), F.count(F.lit(1)).cast("double").alias("n"))
    return out.select("sp", "dp", F.lit("partial").alias("kind"), F.col("dst").alias("key"), "blk", packed(), "n")


def raw(post: DataFrame, feats: DataFrame) -> DataFrame:
    """One row per (sp, dp, src, blk): the source vectors that cross."""
    need = post.select("sp", "dp", "src").distinct()
    return need.join(feats, need["src"] == feats["id"]).select("sp", "dp", F.lit("raw").alias("kind"), F.col("src").alias("key"), "blk", "v", F.lit(1.0).alias("n"))


def messages(routed: DataFrame, feats: DataFrame, weighted: bool = False) -> DataFrame:
    """Everything that crosses parts: partial sums of pre edges, sources of post edges, and edges routed by themselves."""
    out = partials(routed.filter("route = 'pre'"), feats, weighted).unionByName(raw(routed.filter("route = 'post'"), feats))
    return out.unionByName(each(routed.filter("route = 'edge'"), feats, weighted))


def absorb(received: DataFrame, post: DataFrame, weighted: bool = False) -> DataFrame:
    """(dst, blk, v, n) at the receiver: raw messages along post edges, partial sums as they are."""
    r = received.filter("kind = 'raw'").select("sp", "dp", F.col("key").alias("src"), "blk", "v")
    j = post.select("sp", "dp", "src", "dst", "w").join(r, ["sp", "dp", "src"])
    along = j.groupBy("dst", "blk").agg(*block_sums(weight=F.col("w") if weighted else None), F.count(F.lit(1)).cast("double").alias("n")).select("dst", "blk", packed(), "n")
    return along.unionByName(received.filter("kind = 'partial'").select(F.col("key").alias("dst"), "blk", "v", "n"))


def neighbour(local_edges: DataFrame, routed: DataFrame, feats: DataFrame, reduce: str = "sum", weighted: bool = False, through=None) -> DataFrame:
    """The cover-routed layer: (dst, blk, v), equal to :func:`spmm` over local and remote edges.

    ``through`` is applied to the messages (quantize and dequantize).  The two
    message branches meet in one union; only they cross parts.
    """
    if reduce not in ("sum", "mean"):
        raise ValueError("only sums can be taken in two steps here")
    sent = messages(routed, feats, weighted)
    got = absorb(through(sent) if through else sent, routed.filter("route = 'post'"), weighted)
    j = local_edges.join(feats, local_edges["src"] == feats["id"])
    here = j.groupBy("dst", "blk").agg(*block_sums(weight=F.col("w") if weighted else None), F.count(F.lit(1)).cast("double").alias("n")).select("dst", "blk", packed(), "n")
    out = got.unionByName(here).groupBy("dst", "blk").agg(*block_sums(), F.sum("n").alias("n"))
    if reduce == "mean":
        return out.select("dst", "blk", F.transform(packed(), lambda x: x / F.col("n")).alias("v"))
    return out.select("dst", "blk", packed())


def absorb_cogrouped(received: DataFrame, post: DataFrame) -> DataFrame:
    """Raw messages along post edges with one cogrouped Arrow pass per receiving part: (dst, blk, v).

    A control for :func:`absorb`: the part's messages are held as one matrix.
    """
    import numpy as np
    import pyarrow as pa

    from ..session import ship

    ship(received.sparkSession)

    def run(key, msgs: pa.Table, edges: pa.Table) -> pa.Table:
        names = list(zip(msgs["sp"].to_pylist(), msgs["key"].to_pylist(), msgs["blk"].to_pylist()))
        rows: dict[tuple[int, int], list[int]] = {}
        for i, (sp, src, _) in enumerate(names):
            rows.setdefault((sp, src), []).append(i)
        v = np.array(msgs["v"].to_pylist(), dtype=np.float64).reshape(len(names), -1)
        out: dict[tuple[int, int], np.ndarray] = {}
        for sp, src, dst in zip(edges["e_sp"].to_pylist(), edges["e_src"].to_pylist(), edges["e_dst"].to_pylist()):
            for i in rows.get((sp, src), ()):
                at = (dst, names[i][2])
                out[at] = out[at] + v[i] if at in out else v[i]
        return pa.table({"dst": pa.array([k[0] for k in out], pa.int64()), "blk": pa.array([k[1] for k in out], pa.int32()), "v": pa.array([x.tolist() for x in out.values()], pa.list_(pa.float64()))})

    m = received.filter("kind = 'raw'").select("sp", "dp", "key", "blk", "v")
    e = post.select(*[F.col(c).alias(f"e_{c}") for c in ("sp", "dp", "src", "dst")])
    return m.groupBy("dp").cogroup(e.groupBy("e_dp")).applyInArrow(run, "dst long, blk int, v array<double>")
