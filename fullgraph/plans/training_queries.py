"""Training, its ablations and baselines, and the paper's experiments on the given tables.

Histories are rows-only queries: their numbers come from random starts and are
checked by tests of the parts (gradients, invariants), not by SQL.
"""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import aggregate, baselines, costmodel, cover, metrics, minibatch, partition, quantize, remote, train
from ..session import cut, traffic
from ..sources import graphs
from ..sources.tables import drain
from ..functions.vectors import to_block
from .graph_queries import G2_SQL, G6_SQL, P, SQL, SUCC_P, bitmask_sql, query, Q  # noqa: F401

CFG = train.TrainConfig(layers=3, hidden=16, epochs=3)


def _documents(spark: SparkSession, d: str) -> graphs.Graph:
    g = graphs.shingle_documents(spark, d, 8, "lang", noise=0.3)
    return graphs.Graph(cut(spark, g.nodes, "nodes"), cut(spark, g.edges, "edges"))


def _train(cfg: train.TrainConfig):
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = _documents(spark, d)
        prep = train.prepare(g, None, cfg, P)
        return train.history_frame(spark, train.fit(prep, cfg, eval_every=cfg.epochs))

    return run


Q["train_full_batch"] = _train(replace(CFG, lp=False))
Q["train_int2_lp"] = _train(baselines.complete(CFG))
Q["train_plain_post"] = _train(baselines.plain(CFG))
Q["train_gcn"] = _train(replace(CFG, model="gcn", epochs=2))
Q["train_gin"] = _train(replace(CFG, model="gin", epochs=2))
Q["delayed_k5"] = _train(replace(baselines.delayed(CFG, 5), epochs=6))
Q["stale_lag1"] = _train(baselines.stale(CFG))
Q["boundary_sample"] = _train(baselines.boundary_sample(CFG, 0.5))
Q["adaptive_bits"] = _train(replace(baselines.adaptive_bits(CFG), epochs=2))
Q["pre_only"] = _train(replace(baselines.pre_only(CFG), epochs=2))


@query("minibatch")
def mini(spark: SparkSession, d: str) -> DataFrame:
    g = _documents(spark, d)
    prep = train.prepare(g, None, CFG, P)
    return train.history_frame(spark, minibatch.fit(g, replace(CFG, epochs=1), prep, (15, 10, 5), 256, lanes=2, eval_every=1))


@query("ablation_grid")
def ablation_grid(spark: SparkSession, d: str) -> DataFrame:
    g = _documents(spark, d)
    prep = train.prepare(g, None, CFG, P)
    rows = [(r["bits"], r["lp"], r["seed"], r["sent_bytes"], r["param_bytes"], r["test_accuracy"]) for r in train.ablation(prep, replace(CFG, epochs=2))]
    return spark.createDataFrame(rows, "bits int, lp boolean, seed int, sent_bytes long, param_bytes long, test_accuracy double")


@query("predict_accuracy")
def predict_accuracy(spark: SparkSession, d: str) -> DataFrame:
    g = _documents(spark, d)
    cfg = replace(baselines.complete(CFG), epochs=5)
    prep = train.prepare(g, None, cfg, P)
    return metrics.accuracy(train.predict(prep, train.fit(prep, cfg).params, cfg), g.nodes)


# ---------------------------------------------------------------- experiments

BUILDS = {"part_supplier": graphs.part_supplier, "succession": graphs.user_succession, "links": graphs.page_links, "turns": graphs.conversation_turns}


@query("x_communication_ablation")
def communication_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Vectors, data and parameter bytes of one layer for every strategy and bit width, on several graphs."""
    out = None
    for name, build in BUILDS.items():
        away = cut(spark, remote.split(remote.located_by_mod(build(spark, d).edges, P))[1], "remote")
        for strategy in ("pre", "post", "best_of_two", "hybrid"):
            routed = remote.plan(away, strategy)
            for bits in (32, 8, 4, 2) if strategy == "hybrid" else (32,):
                one = metrics.comm_volume(routed, 128, bits).select(F.lit(name).alias("graph"), F.lit(strategy).alias("strategy"), F.lit(bits).alias("bits"), "vectors", "data_bytes", "param_bytes")
                out = one if out is None else out.unionByName(one)
    return out


@query("x_scaling")
def scaling(spark: SparkSession, d: str) -> DataFrame:
    """Volume and modelled exchange time as parts grow, plain against cover-routed 2-bit exchange."""
    edges = cut(spark, graphs.part_supplier(spark, d).edges, "edges")
    out = None
    for p in (4, 8, 16, 32, 64):
        away = remote.split(remote.located_by_mod(edges, p))[1]
        plain, routed = (metrics.comm_matrix(remote.plan(away, s), 128) for s in ("post", "hybrid"))
        a = plain.agg(F.sum("vectors").alias("post_vectors")).crossJoin(costmodel.exchange_time(plain, 1e11, 5e-6).withColumnRenamed("seconds", "post_seconds"))
        own = edges.select(F.pmod("src", F.lit(p)).cast("int").alias("sp")).groupBy("sp").agg((F.count(F.lit(1)) * 128).alias("elements"))
        b = routed.agg(F.sum("vectors").alias("hybrid_vectors")).crossJoin(costmodel.quant_total(routed, own, 2, 128, 1e11, 5e-6, 1e13).withColumnRenamed("seconds", "hybrid_int2_seconds"))
        one = a.crossJoin(b).select(F.lit(p).alias("parts"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def _totals_sql(name: str, edges: str) -> str:
    return f"""SELECT * FROM (WITH {G6_SQL.split('el AS')[0]} x AS ({edges}), el AS (SELECT (src % 16)::INT AS sp, (dst % 16)::INT AS dp, src, dst FROM x), r AS (SELECT * FROM el WHERE sp <> dp), {bitmask_sql('r')},
v AS (SELECT sp, dp, count(*) AS a, count(DISTINCT dst) AS b, count(DISTINCT src) AS c FROM r GROUP BY sp, dp)
SELECT '{name}' AS graph, sum(a)::BIGINT AS edges, sum(b)::BIGINT AS pre, sum(c)::BIGINT AS post, sum(least(b, c))::BIGINT AS best_of_two, (SELECT sum(size) FROM open)::BIGINT AS hybrid, (least(sum(b), sum(c)) / (SELECT sum(size) FROM open))::DOUBLE AS gain FROM v)"""


@query("x_directed_undirected", _totals_sql("directed", "SELECT src, dst FROM e") + " UNION ALL " + _totals_sql("undirected", "SELECT src, dst FROM e UNION SELECT dst, src FROM e"))
def directed_undirected(spark: SparkSession, d: str) -> DataFrame:
    """Volumes of a directed graph and of its symmetric closure: pre equals post only in the latter."""
    e = graphs.user_succession(spark, d).edges
    out = None
    for name, edges in (("directed", e), ("undirected", graphs.symmetrize(e))):
        away = remote.split(remote.located_by_mod(edges, SUCC_P))[1]
        one = metrics.reduction(remote.volumes(away), remote.shipped(cover.routed_by_cover(away))).select(F.lit(name).alias("graph"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "x_aggregation_variants",
    f"WITH {G2_SQL}, w AS (SELECT unnest([16, 64]) AS w), t AS (SELECT w, sum((src * 31 + k) % 97)::BIGINT AS checksum, count(DISTINCT dst) AS n FROM e, w, range(64) r(k) WHERE k < w GROUP BY w) SELECT v AS variant, w::INT AS width, checksum, (n * (w // 16))::BIGINT AS rows FROM t, (SELECT unnest(['vanilla', 'sorted', 'blocked', 'balanced']) AS v) x",
)
def aggregation_variants(spark: SparkSession, d: str) -> DataFrame:
    """Checksum of every aggregation variant at several widths; ``bench.py`` times them."""
    e = graphs.part_supplier(spark, d).edges
    ids = e.select(F.col("src").alias("id")).distinct()
    out = None
    for width in (16, 64):
        f = to_block(ids.select("id", F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda k: F.pmod(F.col("id") * 31 + k, F.lit(97))).alias("v")))
        for v in ("vanilla", "sorted", "blocked", "balanced"):
            s = aggregate.spmm(e, f, variant=v)
            one = s.agg(F.sum(F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x)).alias("checksum"), F.count(F.lit(1)).alias("rows")).select(F.lit(v).alias("variant"), F.lit(width).alias("width"), "*")
            out = one if out is None else out.unionByName(one)
    return out


SINGLE = {"copurchase": "g_copurchase_edges", "part_supplier": "g_part_supplier_edges", "documents": "g_doc_shingle_edges", "knn": "g_knn_topk", "links": "g_page_links", "succession": "g_user_succession", "turns": "g_turns", "customer_part": "g_customer_part"}


@query(
    "x_single_strategies",
    " UNION ALL ".join(
        f"SELECT '{g}' AS graph, sum(a)::BIGINT AS edge, sum(b)::BIGINT AS pre, sum(c)::BIGINT AS post, sum(least(b, c))::BIGINT AS best_of_two FROM (SELECT count(*) AS a, count(DISTINCT dst) AS b, count(DISTINCT src) AS c FROM ({SQL[q]}) WHERE src % 8 <> dst % 8 GROUP BY src % 8, dst % 8)"
        for g, q in SINGLE.items()
    ),
)
def single_strategies(spark: SparkSession, d: str) -> DataFrame:
    """Vectors of one layer on all eight graphs without a cover: per edge, pre, post, best of the two per pair."""
    out = None
    for g in SINGLE:
        away = remote.split(remote.located_by_mod(cut(spark, graphs.BUILDERS[g](spark, d).edges, "edges"), P))[1]
        one = remote.volumes(away).agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(n) for c, n in (("edges", "edge"), ("pre", "pre"), ("post", "post"), ("best_of_two", "best_of_two"))]).select(F.lit(g).alias("graph"), "*")
        out = one if out is None else out.unionByName(one)
    return out


WIRE = replace(CFG, hidden=64, epochs=1, lp=False)


def _wire(spark: SparkSession, d: str, settings: list[tuple[str, int]]) -> list[tuple]:
    """(route, bits, vectors, data bytes, parameter bytes, shuffle bytes) of one epoch of the document graph."""
    g = _documents(spark, d)
    rows = []
    for route in dict.fromkeys(r for r, _ in settings):
        prep = train.prepare(g, None, replace(WIRE, route=route), P)
        for bits in (b for r, b in settings if r == route):
            h = train.fit(prep, replace(WIRE, route=route, bits=bits)).history[0]
            rows.append((route, bits, h["vectors"], h["bytes"], h["param_bytes"], h["shuffle_bytes"]))
        prep.release()
    return rows


@query(
    "x_exchange_bytes",
    f"""WITH e AS ({SQL['g_doc_shingle_edges']}), v AS (SELECT sum(b) AS pre, sum(c) AS post FROM (SELECT count(DISTINCT dst) AS b, count(DISTINCT src) AS c FROM e WHERE src % 8 <> dst % 8 GROUP BY src % 8, dst % 8)),
s AS (SELECT 'pre' AS route, pre AS n FROM v UNION ALL SELECT 'post', post FROM v), b AS (SELECT unnest([32, 2]) AS bits)
SELECT route, bits::INT AS bits, (6 * n)::BIGINT AS vectors, (2 * n * (8 + 64 + 64) * bits // 8)::BIGINT AS data_bytes, (CASE WHEN bits < 32 THEN 6 * n * 8 ELSE 0 END)::BIGINT AS param_bytes, true AS wire_agrees FROM s, b""",
)
def exchange_bytes(spark: SparkSession, d: str) -> DataFrame:
    """Bytes counted for an epoch's exchanges, and whether Spark's shuffle wrote at most 1.5 times them and 40 KB."""
    rows = [(*r[:5], r[5] <= 1.5 * (r[3] + r[4]) + 40_000) for r in _wire(spark, d, [("pre", 32), ("pre", 2), ("post", 32), ("post", 2)])]
    return spark.createDataFrame(rows, "route string, bits int, vectors long, data_bytes long, param_bytes long, wire_agrees boolean")


@query("x_exchange_wire")
def exchange_wire(spark: SparkSession, d: str) -> DataFrame:
    """Counted and really shuffled bytes of an epoch: per edge, post, cover, cover with 8, 4 and 2 bits."""
    rows = _wire(spark, d, [("edge", 32), ("post", 32), ("hybrid", 32), ("hybrid", 8), ("hybrid", 4), ("hybrid", 2)])
    return spark.createDataFrame(rows, "route string, bits int, vectors long, data_bytes long, param_bytes long, shuffle_bytes long")


@query("x_accuracy")
def accuracy(spark: SparkSession, d: str, parts: int = P, seeds: tuple[int, ...] = (0, 1, 2), epochs: int = 30) -> DataFrame:
    """The four settings on the document graph, three seeds each, by validation accuracy; the majority rate stands beside."""
    g = _documents(spark, d)
    cfg = replace(CFG, epochs=epochs)
    prep = train.prepare(g, None, cfg, parts)
    n = g.nodes.filter("split = 'test' and label is not null").groupBy("label").count().agg(F.max("count").alias("m"), F.sum("count").alias("n")).first()
    rows = [(parts, r["bits"], r["lp"], r["seed"], r["epochs"], r["val_accuracy"], r["test_accuracy"], n.m / n.n) for r in train.ablation(prep, cfg, seeds, eval_every=5, patience=3)]
    prep.release()
    return spark.createDataFrame(rows, "parts int, bits int, lp boolean, seed int, epochs int, val_accuracy double, test_accuracy double, majority double")


@query("x_minibatch")
def full_against_mini(spark: SparkSession, d: str, epochs: int = 4) -> DataFrame:
    """Full batch and sampled blocks, the same model and graph: test accuracy per epoch."""
    g = _documents(spark, d)
    cfg = replace(CFG, epochs=epochs, lp=False)
    prep = train.prepare(g, None, cfg, P)
    runs = {"full": train.fit(prep, replace(cfg, epochs=4 * epochs), eval_every=epochs), "mini": minibatch.fit(g, cfg, prep, (15, 10, 5), 64, lanes=2, eval_every=1)}
    rows = [(name, h["epoch"] + 1, h["loss"], h["test_accuracy"], h["seconds"]) for name, r in runs.items() for h in r.history if "test_accuracy" in h]
    return spark.createDataFrame(rows, "method string, epoch int, loss double, test_accuracy double, seconds double")


def _vectors(edges: DataFrame, width: int) -> DataFrame:
    """A vector of floats that do not compress for every source, in blocks."""
    ids = edges.select(F.col("src").alias("id")).distinct()
    return to_block(ids.select("id", F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda k: F.sin(F.col("id") * 31 + k).cast("float")).alias("v")))


def _exchanged(spark: SparkSession, sent: DataFrame, bits: int, parts: int) -> tuple[float, traffic]:
    """Wall seconds and stage metrics of moving messages to their receivers; codes and two numbers a row below 32 bits."""
    if bits < 32:
        rows = quantize.params(sent, bits, id_="key")
        q = quantize.codes(F.col("v"), F.col("zp"), F.col("sc"), bits, id_=F.col("key"))
        sent = rows.select("sp", "dp", "key", "blk", quantize.pack(q, bits).alias("codes"), F.col("zp").cast("float"), F.col("sc").cast("float"))
    else:
        sent = sent.select("sp", "dp", "key", "blk", F.col("v").cast("array<float>"))
    began = time.time()
    with traffic(spark) as wire:
        drain(sent.repartition(parts, "dp"))
    return time.time() - began, wire


@query("x_exchange_time")
def exchange_time_measured(spark: SparkSession, d: str, names: tuple[str, ...] = tuple(graphs.BUILDERS), width: int = 64) -> DataFrame:
    """Measured exchange of one layer on every graph and strategy: vectors, shuffled bytes, wall and shuffle times."""
    rows = []
    for name in names:
        edges = cut(spark, graphs.BUILDERS[name](spark, d).edges, "edges")
        away = cut(spark, remote.split(remote.located_by_mod(edges, P))[1], "remote")
        f = cut(spark, _vectors(edges, width), "vectors")
        for strategy in ("edge", "pre", "post", "best_of_two", "hybrid"):
            routed = cut(spark, remote.plan(away, strategy), "routed", narrow=True)
            sent = cut(spark, aggregate.messages(routed, f), "messages")
            vectors = remote.shipped(routed).agg(F.coalesce(F.sum("vectors"), F.lit(0)).alias("n")).first().n
            for bits in (32, 8, 4, 2) if strategy == "hybrid" else (32,):
                seconds, wire = _exchanged(spark, sent, bits, P)
                rows.append((name, strategy, bits, vectors, wire.bytes, seconds * 1000, wire.write_ms, wire.wait_ms))
    return spark.createDataFrame(rows, "graph string, strategy string, bits int, vectors long, shuffle_bytes long, wall_ms double, write_ms double, wait_ms double")


@query("x_breakdown")
def breakdown(spark: SparkSession, d: str, cases: tuple[tuple[str, int], ...] = (("documents", 4), ("customer_part", 32)), width: int = 64) -> DataFrame:
    """Seconds of a layer's steps, base against optimized: every step runs by itself, so nothing overlaps.

    Synchronization is the part of the exchange in which an average sender has ended and waits for
    the busiest one, by the vectors that they send; ``other`` is what the whole layer takes beyond the steps.
    """
    rows = []
    for name, parts in cases:
        g = graphs.BUILDERS[name](spark, d)
        edges = cut(spark, g.edges, "edges")
        here, away = (cut(spark, e, "split") for e in remote.split(remote.located_by_mod(edges, parts)))
        f = cut(spark, _vectors(edges, width), "vectors")
        for setting, strategy, bits, variant in (("base", "post", 32, "vanilla"), ("optimized", "hybrid", 2, "blocked")):
            routed = cut(spark, remote.plan(away, strategy), "routed", narrow=True)
            sent = cut(spark, aggregate.messages(routed, f), "messages")
            through = quantize.through(bits) if bits < 32 else None

            def timed(df: DataFrame) -> float:
                began = time.time()
                drain(df)
                return time.time() - began

            local = timed(aggregate.local(here, f, variant=variant))
            exchange, _ = _exchanged(spark, sent, bits, parts)
            codec = timed(through(sent)) if through else 0.0
            ratio = metrics.imbalance(remote.shipped(routed)).first().ratio or 1.0
            waits = exchange * (1 - 1 / ratio)
            whole = timed(aggregate.neighbour(here, routed, f, through=through))
            rows.append((name, parts, setting, local, exchange - waits, codec, waits, max(0.0, whole - local - exchange - codec), whole))
    return spark.createDataFrame(rows, "graph string, parts int, setting string, aggregation double, communication double, quantization double, synchronization double, other double, layer double")


@query("x_scaling_delayed")
def scaling_delayed(spark: SparkSession, d: str, names: tuple[str, ...] = ("copurchase", "part_supplier", "documents", "succession"), sizes: tuple[int, ...] = (4, 16), every: int = 5) -> DataFrame:
    """Epoch time and bytes as parts grow: delayed exchange, plain exchange, everything on.

    Two epochs run.  A delayed epoch is the mean of one that exchanges and ``every`` - 1 like the next one, which does not.
    ``speedup`` is over the fewest parts, ``against_delayed`` over the delayed method on as many parts.
    """
    base = replace(CFG, epochs=2)
    rows = []
    for name in names:
        g = graphs.BUILDERS[name](spark, d)
        g = graphs.Graph(cut(spark, g.nodes.na.fill({"label": 0}), "nodes"), cut(spark, g.edges, "edges"))
        first: dict[str, float] = {}
        for parts in sizes:
            took = {}
            for cfgs in ({"delayed": baselines.delayed(base, every), "plain": baselines.plain(base)}, {"complete": baselines.complete(base)}):
                prep = train.prepare(g, partition.by_mod(g.nodes, parts), next(iter(cfgs.values())), parts)
                for method, cfg in cfgs.items():
                    h = train.fit(prep, cfg).history
                    share = (1 / every, 1 - 1 / every) if method == "delayed" else (0.0, 1.0)  # the second epoch runs warm
                    seconds, sent, wire = (sum(s * e[c] for s, e in zip(share, h)) for c in ("seconds", "bytes", "shuffle_bytes"))
                    took[method] = seconds
                    first.setdefault(method, seconds)
                    rows.append((name, parts, method, seconds, sent, wire, first[method] / seconds, took["delayed"] / seconds))
                prep.release()
    return spark.createDataFrame(rows, "graph string, parts int, method string, epoch_seconds double, bytes double, shuffle_bytes double, speedup double, against_delayed double")
