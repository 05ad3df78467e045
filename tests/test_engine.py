"""The method's worked example, invariants, kernels against brute force, and training checks."""

import itertools
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from fullgraph.functions import vectors
from fullgraph.operators import aggregate, baselines, costmodel, cover, layers, metrics, minibatch, partition, propagate, quantize, relational, remote, train
from fullgraph.plans import graph_queries, training_queries
from fullgraph.sources import graphs

D = "/root/testdata/sf0.001"


# ---------------------------------------------------------------- graphs


def test_document_graph_is_built_in_arrays(spark, tmp_path):
    """Edges and features against brute force on odd texts; no row for every word or pair of characters."""
    texts = ["a b c d e", "x a b c", None, "", "é\x85ü b c d", "b c d", "Q" * 3 + "\u00a0y z", "日本語 日本語 日本語 日本語", "one two", "日本語 日本語 日本語", "😀é 😀é 😀é", *["q r s"] * 11]
    spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long").coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    g = graphs.shingle_documents(spark, str(tmp_path), 8)
    grams = {}
    for i, t in enumerate(texts):
        w = (t or "").encode().split()
        for j in range(len(w) - 2):
            grams.setdefault(tuple(w[j : j + 3]), set()).add(i)
    want = {(a, b) for ids in grams.values() if 2 <= len(ids) <= 10 for a in ids for b in ids if a != b}
    assert want and sorted((r.src, r.dst) for r in g.edges.collect()) == sorted(want)
    for r in g.nodes.collect():
        t, counts = (texts[r.id] or "").lower(), np.zeros(8)
        for j in range(len(t) - 1):
            counts[zlib.crc32(t[j : j + 2].encode()) % 8] += 1
        assert np.allclose(r.feat, counts / (np.linalg.norm(counts) or 1)), r.id
    for df in (g.edges, g.nodes):
        assert "Generate" not in df._jdf.queryExecution().optimizedPlan().toString()


# ---------------------------------------------------------------- covers


def brute_cover(edges):
    us = sorted({u for u, _ in edges})
    return min(len(us) - len(s) + len({v for u, v in edges if u in s}) for k in range(len(us) + 1) for s in map(set, itertools.combinations(us, k)))


def test_cover_is_minimum_and_canonical():
    rng = random.Random(0)
    for _ in range(150):
        edges = sorted({(rng.randint(0, 6), rng.randint(0, 6)) for _ in range(rng.randint(1, 18))})
        us, u = np.unique([a for a, _ in edges], return_inverse=True)
        vs, v = np.unique([b for _, b in edges], return_inverse=True)
        for side in ("src", "dst"):
            a, b, size = cover.konig_cover(u, v, side)
            assert a.sum() + b.sum() == size == brute_cover(edges)
            assert all(a[x] or b[y] for x, y in zip(u, v))
        order = np.random.default_rng(1).permutation(len(u))
        assert (cover.konig_cover(u[order], v[order])[0] == cover.konig_cover(u, v)[0]).all()


def test_long_path_needs_no_recursion():
    n = 3000
    u, v = np.repeat(np.arange(n), 2)[:-1], np.repeat(np.arange(n), 2)[1:]
    a, b, size = cover.konig_cover(u, np.concatenate([v, []]).astype(int))
    assert size == n or size == n - 1
    assert a.sum() + b.sum() == size


def test_worked_example(spark):
    e = graph_queries.worked_edges(spark)
    v = remote.volumes(e).first()
    assert (v.edges, v.pre, v.post) == (5, 3, 3)
    routed = cover.routed_by_cover(e)
    assert sorted((r.src, r.dst, r.route) for r in routed.collect()) == [(4, 1, "post"), (4, 2, "post"), (4, 3, "post"), (5, 2, "pre"), (6, 2, "pre")]
    assert {(r.side, r.id) for r in cover.cover_of(routed).collect()} == {("src", 4), ("dst", 2)}
    assert remote.shipped(routed).first().vectors == 2


@pytest.mark.parametrize("name", ["part_supplier", "succession", "links", "turns"])
def test_invariants(spark, name):
    g = graphs.BUILDERS[name](spark, D)
    edges = g.edges.cache()
    for p in (1, 4):
        here, away = remote.split(remote.located_by_mod(edges, p))
        if p == 1:
            assert away.count() == 0  # one part sends nothing
            continue
        routed = cover.routed_by_cover(away).cache()
        assert routed.select("src", "dst").exceptAll(away.select("src", "dst")).count() == 0 and routed.count() == away.count()
        v = {(r.sp, r.dp): r for r in remote.volumes(away).collect()}
        h = {(r.sp, r.dp): r.vectors for r in remote.shipped(routed).collect()}
        m = {(r.sp, r.dp): r.matched for r in cover.matching_sizes(away).collect()}
        assert h == m and all(h[k] <= v[k].best_of_two for k in v)
        if name in ("part_supplier", "links"):
            assert sum(r.pre for r in v.values()) == sum(r.post for r in v.values())
        if name == "turns":
            assert all(h[k] == v[k].edges for k in v)


def test_components_covers_and_large_pairs(spark):
    away = remote.split(remote.located_by_mod(graphs.user_succession(spark, D).edges, 3))[1].cache()
    size = remote.shipped(cover.routed_by_cover(away)).agg(F.sum("vectors")).first()[0]
    comps = cover.components(away)
    parts = cover.routed_by_cover(comps.select(F.col("sp"), (F.col("dp") * 1000 + F.dense_rank().over(__import__("pyspark").sql.Window.partitionBy("sp", "dp").orderBy("component"))).cast("int").alias("dp"), "src", "dst", "w"))
    assert remote.shipped(parts).agg(F.sum("vectors")).first()[0] == size
    split = cover.routed_by_cover(away, max_pair_edges=3, approximate=True)
    assert split.count() == away.count()
    assert size <= remote.shipped(split).agg(F.sum("vectors")).first()[0] <= 2 * size
    largest = comps.groupBy("sp", "dp", "component").count().agg(F.max("count")).first()[0]
    whole = cover.routed_by_cover(away, max_pair_edges=largest)  # pairs go through components, the cover stays the minimum
    assert remote.shipped(whole).agg(F.sum("vectors")).first()[0] == size
    with pytest.raises(Exception, match="more than 3"):
        cover.routed_by_cover(away, max_pair_edges=3).count()
    with pytest.raises(RuntimeError, match="still change"):
        cover.components(away, rounds=1)
    greedy = cover.greedy_cover(away)
    assert size <= greedy.count() <= 2 * size
    left, chosen = cover.reduce_leaves(away, 2)
    rest = remote.shipped(cover.routed_by_cover(left)).agg(F.sum("vectors")).first()[0] or 0
    assert chosen.count() + rest == size


def test_odd_graphs(spark):
    none = spark.createDataFrame([], "src long, dst long, w double")
    here, away = remote.split(remote.located_by_mod(none, 4))
    assert cover.routed_by_cover(away).count() == 0 and remote.volumes(away).count() == 0
    loops = spark.createDataFrame([(1, 1, 1.0), (1, 2, 1.0), (1, 2, 1.0), (5, 9, 1.0)], "src long, dst long, w double")
    f = vectors.to_block(spark.createDataFrame([(1, [1.0, 2.0]), (2, [3.0, 4.0])], "id long, v array<double>"))
    got = {(r.dst, r.blk): list(r.v)[:2] for r in aggregate.spmm(loops, f).collect()}
    assert got == {(1, 0): [1.0, 2.0], (2, 0): [2.0, 4.0]}  # node 5 has no vector
    assert graphs.symmetrize(loops).count() == 4 and graphs.symmetrize(loops, self_loops=True).count() == 5
    assert relational.connected(loops).agg(F.countDistinct("component")).first()[0] == 2


# ---------------------------------------------------------------- plans


def test_routed_plan_has_no_product_and_no_broadcast_of_vectors(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        here, away = remote.split(graph_queries.g2_located(spark, D))
        routed = remote.plan(away, "best_of_two")
        text = aggregate.neighbour(here, routed, graph_queries.g2_features(spark, D))._jdf.queryExecution().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "CartesianProduct" not in text and "BroadcastNestedLoop" not in text and "BroadcastExchange" not in text
    assert "partial_sum" in text


@pytest.mark.parametrize("name", ["convergence_bound", "cost_speedup_curve", "worked_example", "udtf_cover"])
def test_queries_read_a_given_table(spark, name):
    from fullgraph.plans import surround_queries

    df = surround_queries.Q[name](spark, D)
    assert "FileScan parquet" in df._jdf.queryExecution().executedPlan().toString() and df.count() > 0


def test_filters_reach_the_scan(spark):
    text = graphs.part_supplier(spark, D).edges._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity)" in text and "l_extendedprice" not in text.split("== Physical Plan ==")[1]


# ---------------------------------------------------------------- quantization


def test_quantize_rows_round_trip():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(7, 13))
    x[3] = 2.5  # no range
    for bits in (2, 4, 8):
        for g in (1, 4):
            for r in (None, rng):
                q, zp, sc = quantize.quantize_rows(x, bits, r, g)
                assert q.dtype == np.uint8 and q.shape[1] == -(-13 * bits // 8)
                err = np.abs(quantize.dequantize_rows(q, zp, sc, bits, 13) - x)
                assert (err <= sc[:, None] * (0.5 if r is None else 1) + 1e-5).all()
    many = np.mean([quantize.dequantize_rows(*quantize.quantize_rows(x, 2, rng), 2, 13) for _ in range(600)], axis=0)
    assert np.abs(many - x).max() < 0.15  # unbiased


@pytest.mark.parametrize("n", [0, 5, 30_011])
def test_adaptive_widths_follow_exact_shares(spark, n):
    rows = quantize.adaptive(spark.range(n).select("id", F.array(F.lit(0.0), F.sqrt(F.col("id") + 1)).alias("v"))).groupBy("bits").count().collect()
    low, middle = -(-n // 2), -(-n * 8 // 10)
    assert {r.bits: r["count"] for r in rows} == {b: c for b, c in ((2, low), (4, middle - low), (8, n - middle)) if c}


def test_sql_pack_matches_numpy(spark):
    df = spark.createDataFrame([(1, [0.0, 1.0, 0.25, 0.8, 0.5]), (2, [3.0] * 5)], "id long, v array<double>")
    for bits in (2, 4, 8):
        q = quantize.encode(df, bits).select("id", "q", quantize.pack(F.col("q"), bits).alias("c"), quantize.unpack(quantize.pack(F.col("q"), bits), bits, 5).alias("u"))
        fused = {r.id: bytes(r.codes) for r in quantize.fused(df, bits).collect()}
        for r in q.collect():
            assert list(r.q) == list(r.u) and bytes(r.c) == fused[r.id]
        back = quantize.unfused(quantize.fused(df, bits), 5)
        assert metrics.quant_error(df, back, quantize.params(df, bits)).first().worst_in_scales <= 0.5001


def test_int2_messages_stay_close(spark):
    here, away = remote.split(graph_queries.g2_located(spark, D))
    f = graph_queries.g2_features(spark, D).select("id", "blk", F.transform("v", lambda x: x / float(1 << 20)).alias("v"))
    routed = cover.routed_by_cover(away)
    a = aggregate.neighbour(here, routed, f, reduce="mean")
    b = aggregate.neighbour(here, routed, f, reduce="mean", through=quantize.through(8))
    gap = a.join(b.withColumnRenamed("v", "u"), ["dst", "blk"]).select(F.array_max(F.zip_with("v", "u", lambda x, y: F.abs(x - y))).alias("g")).agg(F.max("g")).first()[0]
    assert 0 <= gap < 0.02


# ---------------------------------------------------------------- cost model


def test_cost_model():
    assert costmodel.speedup(100, 100, 16, 0) == pytest.approx(16 / 1.5)
    assert costmodel.speedup(1e9, 1e9, 16, 0) == pytest.approx(16)
    assert costmodel.speedup(100, 100, 16, 1e9) == pytest.approx(1, abs=1e-6)
    assert costmodel.speedup(100, 0.1, 16, 0) < 1  # slow codecs can lose
    a = costmodel.ratios(1e6, 1e4, 1e12, 1e10, 2, 1e-5)
    elements, params, bw, th, lat, bits = 1e6, 1e4, 1e10, 1e12, 1e-5, 2
    plain = elements * 32 / bw + lat
    quant = 2 * elements * (32 + bits) / th + (elements * bits + params * 32) / bw + lat
    assert costmodel.speedup(**a) == pytest.approx(plain / quant)
    assert costmodel.convergence_bound(2, 1, 10**9, 0.1, 1, 0) == pytest.approx(0, abs=1e-6)
    assert costmodel.crossover_saving(64, 48, 1e-5) == pytest.approx(16e-5)


# ---------------------------------------------------------------- partitioners


def test_partitioners(spark):
    g = graphs.part_supplier(spark, D)
    nodes = g.nodes.cache()
    n = nodes.count()
    cuts = {}
    for name, parts in (("mod", partition.by_mod(nodes, 4)), ("multilevel", partition.multilevel(nodes, g.edges, 4)), ("propagate", partition.propagate(nodes, g.edges, 4, 2))):
        rows = parts.collect()
        assert len(rows) == n == len({r.id for r in rows}) and {r.part for r in rows} <= set(range(4))
        cuts[name] = metrics.partition_quality(remote.located(g.edges, parts)).first().cut_ratio
    assert cuts["multilevel"] < cuts["mod"]
    weights = partition.node_weights(nodes, g.edges)
    load = metrics.part_load(nodes, partition.multilevel(nodes, g.edges, 4), weights).collect()
    assert max(r.weight for r in load) < 2 * sum(r.weight for r in load) / len(load)


@pytest.mark.parametrize("n", [0, 3, 30_011])
def test_ranges_are_cut_at_exact_quantiles(spark, n):
    rows = partition.by_range(spark.range(n), 8).collect()
    cuts = [max(1, -(-n * i // 8)) - 1 for i in range(1, 8)]
    assert {r.id: r.part for r in rows} == {i: sum(c < i for c in cuts) for i in range(n)}


# ---------------------------------------------------------------- joins


def test_nested_loop_join_compares_blocks(spark, tmp_path):
    keys = [1, 2, 127, 128, 300, 300, None]
    orders = [(k, p) for k in (1, 2, 2, 5, 128, 300, 301, None) for p in ("high", "low", None)]
    spark.createDataFrame([(k,) for k in keys], "c_custkey long").write.parquet(str(tmp_path / "customer.parquet"))
    spark.createDataFrame(orders, "o_custkey long, o_orderpriority string").write.parquet(str(tmp_path / "orders.parquet"))
    from fullgraph.plans import surround_queries

    df = surround_queries.Q["join_shuffle_replicate_nl"](spark, str(tmp_path))
    assert {r.o_orderpriority: r.n for r in df.collect()} == {p: 6 for p in ("high", "low", None)}
    product = df._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in product and product.count("collect_list") >= 2


# ---------------------------------------------------------------- training


def tiny(spark, model="sage"):
    edges = [(0, 1), (1, 2), (2, 0), (3, 1), (4, 2), (5, 4), (3, 5), (0, 4), (5, 0)]
    rng = np.random.default_rng(2)
    nodes = spark.createDataFrame([(i, rng.normal(size=3).tolist(), i % 2, "train") for i in range(6)], "id long, feat array<double>, label int, split string")
    return graphs.Graph(nodes, spark.createDataFrame([(a, b, 1.0) for a, b in edges], "src long, dst long, w double"))


BASE = train.TrainConfig(layers=2, hidden=4, epochs=2, dropout=0.0, lp=False, bits=32)


def one_epoch(spark, g, cfg, p, params, parts=None):
    prep = train.prepare(g, parts or partition.by_mod(g.nodes, p), cfg, p)
    return train.epoch_total(prep, params, cfg, 0)


@pytest.mark.parametrize("model", ["sage", "gcn", "gin"])
def test_gradients_and_partition_independence(spark, model):
    from dataclasses import replace

    g = tiny(spark)
    cfg = replace(BASE, model=model, lp=True, lp_rate=0.3)
    params = train.init_params(cfg, 3, 2)
    whole = one_epoch(spark, g, cfg, 1, params)
    split = one_epoch(spark, g, cfg, 3, params)
    assert whole["stats"]["loss"] == pytest.approx(split["stats"]["loss"], rel=1e-5)
    for k in whole["grads"]:
        assert np.allclose(whole["grads"][k], split["grads"][k], atol=1e-4), k
    # numerical gradient, on the one-part worker
    prep = train.prepare(g, partition.by_mod(g.nodes, 1), cfg, 1)
    part = train.joined({r.seq: bytes(r.payload) for r in prep.table.collect()})

    def loss(p):
        w = train.Worker(part, p, cfg, 0, "train", None)
        for t in range(cfg.layers + 1):
            w.step(t, {})
        return w.stats["loss"]

    rng = np.random.default_rng(0)
    for k, grad in whole["grads"].items():
        at = tuple(rng.integers(0, s) for s in grad.shape)
        up, down = ({**params, k: params[k].copy()} for _ in range(2))
        up[k][at] += 1e-5
        down[k][at] -= 1e-5
        assert (loss(up) - loss(down)) / 2e-5 == pytest.approx(grad[at], abs=2e-3), k


def test_routes_give_one_result_and_hybrid_sends_least(spark):
    from dataclasses import replace

    g = graphs.part_supplier(spark, D)
    nodes = g.nodes.withColumn("label", F.coalesce("label", F.lit(0)))
    g = graphs.Graph(nodes.cache(), g.edges.cache())
    params = train.init_params(BASE, 8, 8)
    out = {r: one_epoch(spark, g, replace(BASE, route=r), 4, params) for r in ("pre", "post", "hybrid", "edge")}
    assert out["edge"]["stats"]["loss"] == pytest.approx(out["post"]["stats"]["loss"], rel=1e-5) and out["edge"]["bytes"] > out["post"]["bytes"]
    for k, x in out["edge"]["grads"].items():
        assert np.allclose(x, out["hybrid"]["grads"][k], atol=1e-3)
    assert out["pre"]["stats"]["loss"] == pytest.approx(out["post"]["stats"]["loss"], rel=1e-5) == pytest.approx(out["hybrid"]["stats"]["loss"], rel=1e-5)
    assert out["hybrid"]["bytes"] < 0.7 * min(out["pre"]["bytes"], out["post"]["bytes"])
    small = one_epoch(spark, g, replace(BASE, route="hybrid", bits=2), 4, params)
    assert small["bytes"] * 15 < out["hybrid"]["bytes"] + 15 * 4 * 200 and small["param_bytes"] > 0


def test_delays(spark):
    from dataclasses import replace

    g = tiny(spark)
    cfg = replace(BASE, epochs=3, route="post")
    prep = train.prepare(g, partition.by_mod(g.nodes, 3), cfg, 3)
    sync = [r["loss"] for r in train.fit(prep, cfg).history]
    assert [r["loss"] for r in train.fit(prep, baselines.delayed(cfg, 1)).history] == pytest.approx(sync)
    late = train.fit(prep, baselines.delayed(cfg, 2)).history
    assert [r["bytes"] > 0 for r in late] == [True, False, True]
    stale = train.fit(prep, baselines.stale(cfg)).history
    assert stale[0]["loss"] == pytest.approx(sync[0]) and all(r["bytes"] > 0 for r in stale)
    half = train.fit(prep, baselines.boundary_sample(cfg, 0.5)).history
    assert sum(r["bytes"] for r in half) < sum(r["bytes"] for r in train.fit(prep, cfg).history)


def test_only_messages_are_exchanged(spark):
    from dataclasses import replace

    rng = np.random.default_rng(8)
    n, width = 400, 64
    nodes = spark.createDataFrame([(i, rng.normal(size=width).tolist(), i % 3, "train") for i in range(n)], "id long, feat array<double>, label int, split string")
    edges = spark.createDataFrame([(i, int(j), 1.0) for i in range(n) for j in rng.choice(n, 6, replace=False)], "src long, dst long, w double")
    g = graphs.Graph(nodes.cache(), edges.cache())
    wire = {}
    for name, cfg in (("plain", baselines.plain(BASE)), ("complete", baselines.complete(BASE))):
        cfg = replace(cfg, hidden=64, epochs=2, lp=False)
        r = train.fit(train.prepare(g, partition.by_mod(g.nodes, 4), cfg, 4), cfg)
        counted = r.sent_bytes + r.param_bytes
        wire[name] = r.shuffle_bytes
        # heads, names and compression: a part's state would be many times this
        assert 0.5 * counted < r.shuffle_bytes < 1.5 * counted + 40_000, (name, counted, r.shuffle_bytes)
    assert wire["plain"] > 5 * wire["complete"]


def test_sweep_equals_single_runs(spark):
    from dataclasses import replace

    g = tiny(spark)
    cfg = replace(BASE, epochs=2, bits=4, optimizer="sgd", dropout=0.5)
    prep = train.prepare(g, partition.by_mod(g.nodes, 3), cfg, 3)
    cfgs = [replace(cfg, seed=s, lp=lp) for s in (0, 1) for lp in (False, True)]
    for c, r in zip(cfgs, train.fit_many(prep, cfgs)):
        alone = train.fit(prep, c)
        assert [h["loss"] for h in r.history] == pytest.approx([h["loss"] for h in alone.history])
        assert all(np.allclose(r.params[k], alone.params[k]) for k in r.params)
    stopped = train.fit(prep, replace(cfg, epochs=6), eval_every=1, patience=2)
    assert 1 <= len(stopped.history) <= 6
    with pytest.raises(ValueError):
        train.fit_many(prep, [cfg, replace(cfg, layers=3)])


def test_minibatch_visits_every_training_node(spark):
    from dataclasses import replace

    rng = np.random.default_rng(5)
    n = 90
    rows = [(i, (rng.normal(size=4) + 3 * (np.arange(4) == i % 3)).tolist(), i % 3, graphs_split(i)) for i in range(n)]
    edges = [(i, int((i + 3 * k) % n), 1.0) for i in range(n) for k in (1, 2, 5)]
    g = graphs.Graph(spark.createDataFrame(rows, "id long, feat array<double>, label int, split string"), spark.createDataFrame(edges, "src long, dst long, w double"))
    seeds = g.nodes.filter("split = 'train'").select(F.pmod(F.xxhash64("id"), F.lit(4)).cast("int").alias("block"), "id")
    nodes, taken = minibatch.sample_blocks(g, seeds, (2, 1), 0)
    assert nodes.filter("is_seed").count() == seeds.count() == nodes.filter("is_seed").select("id").distinct().count()
    assert taken.groupBy("block", "dst").count().agg(F.max("count")).first()[0] <= 3
    assert taken.join(g.edges, ["src", "dst"], "left_anti").count() == 0
    cfg = replace(BASE, epochs=6, hidden=8, lr=0.05)
    prep = train.prepare(g, partition.by_mod(g.nodes, 2), cfg, 2)
    r = minibatch.fit(g, cfg, prep, (3, 2), 16, lanes=2, eval_every=6)
    assert r.history[-1]["loss"] < r.history[0]["loss"] and r.history[-1]["test_accuracy"] > 0.6


def test_aggregation_variants_agree(spark):
    rng = random.Random(6)
    rows = [(rng.randint(0, 30), 0 if rng.random() < 0.5 else rng.randint(0, 30), float(rng.randint(1, 3))) for _ in range(400)]  # node 0 is a hub
    e = spark.createDataFrame(rows, "src long, dst long, w double")
    f = vectors.to_block(spark.createDataFrame([(i, [float(i * k % 7) for k in range(40)]) for i in range(30)], "id long, v array<double>"))
    for weighted in (False, True):
        out = {v: {(r.dst, r.blk): list(r.v) for r in aggregate.spmm(e, f, weighted=weighted, variant=v).collect()} for v in ("vanilla", "sorted", "blocked", "balanced")}
        assert out["vanilla"] == out["blocked"] == out["sorted"] == out["balanced"]
    lanes = aggregate.work_lanes(e, 4).collect()
    assert next(r.salts for r in lanes if r.dst == 0) > 1 and {r.lane for r in lanes} <= set(range(4))
    none = e.limit(0)
    assert all(aggregate.spmm(none, f, variant=v).count() == 0 for v in ("vanilla", "sorted", "balanced"))


def test_narrow_rows_reach_python_without_a_bound_on_bytes(spark):
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before, seen = spark.conf.get(key), []
    prepare_cut = train.cut

    def spy(session, df, name, narrow=False):
        seen.append((name, narrow, "MapInArrow" in df._jdf.queryExecution().executedPlan().toString()))
        return prepare_cut(session, df, name, narrow)

    train.cut = spy
    try:
        prep = train.prepare(tiny(spark), partition.by_mod(tiny(spark).nodes, 3), BASE, 3)
    finally:
        train.cut = prepare_cut
    assert all(narrow for _, narrow, python in seen if python) and any(python for *_, python in seen)
    assert spark.conf.get(key) == before and sorted({r.part for r in prep.table.collect()}) == [0, 1, 2]


def test_isolated_nodes_stay_off_the_driver(spark):
    nodes = spark.range(300).select("id", F.lit("train").alias("split"))
    edges = spark.createDataFrame([(i, i + 1, 1.0) for i in range(20)], "src long, dst long, w double")
    got = partition.multilevel(nodes, edges, 4, max_driver_nodes=30, target=40)
    assert got.count() == 300 == got.select("id").distinct().count()


def test_training_learns(spark):
    from dataclasses import replace

    rng = np.random.default_rng(3)
    n = 120
    rows = [(i, (rng.normal(size=4) + 3 * (np.arange(4) == i % 3)).tolist(), i % 3, graphs_split(i)) for i in range(n)]
    edges = [(i, int((i + 3 * k) % n), 1.0) for i in range(n) for k in (1, 2, 5)]
    g = graphs.Graph(spark.createDataFrame(rows, "id long, feat array<double>, label int, split string"), spark.createDataFrame(edges, "src long, dst long, w double"))
    cfg = replace(baselines.complete(BASE), epochs=12, hidden=8, lr=0.05)
    prep = train.prepare(g, partition.by_mod(g.nodes, 4), cfg, 4)
    r = train.fit(prep, cfg)
    assert r.history[-1]["loss"] < 0.7 * r.history[0]["loss"]
    assert train.evaluate(prep, r.params, cfg)["test_accuracy"] > 0.8
    acc = metrics.accuracy(train.predict(prep, r.params, cfg), g.nodes).collect()
    assert {x.split for x in acc} == {"train", "val", "test"}


def graphs_split(i):
    return "train" if i % 10 <= 4 else "val" if i % 10 == 5 else "test"


def test_label_masks_never_leak(spark):
    n = graph_queries._labelled(spark, D)
    m = {r.id: r.shown for r in propagate.mask(n, 0.5, 3).collect()}
    ids = np.array(sorted(m))
    assert (propagate.shown_rows(ids, 0.5, 3) == np.array([m[i] for i in ids])).all()
    seen = propagate.inject(n, None, [[100.0], [200.0]], "infer").filter("split <> 'train'").collect()
    assert all(r.feat[0] < 100 for r in seen)


def test_layer_kernels():
    rng = np.random.default_rng(4)
    x, g, b = rng.normal(size=(5, 6)), rng.normal(size=6), rng.normal(size=6)
    y, saved = layers.norm_rows(x, g, b)
    d = rng.normal(size=x.shape)
    dx, dg, db = layers.norm_rows_back(d, g, saved)
    for i in ((0, 1), (4, 5)):
        up, down = x.copy(), x.copy()
        up[i] += 1e-6
        down[i] -= 1e-6
        assert ((layers.norm_rows(up, g, b)[0] - layers.norm_rows(down, g, b)[0]) * d).sum() / 2e-6 == pytest.approx(dx[i], abs=1e-4)
    seg = train._segments(np.array([2, 0, 2]), np.array([1, 1, 0]), np.array([1.0, 2.0, 3.0]))
    v = np.array([[1.0], [10.0]])
    assert train.segment_sum(3, seg, v).ravel().tolist() == [20.0, 0.0, 13.0] == train.segment_sum(3, seg, v, 1).ravel().tolist()


def test_all_of_lineitem_is_routed(spark, tmp_path):
    rng = random.Random(31)
    lines = [(rng.randint(1, 24), rng.randint(1, 40), float(rng.randint(1, 50)), rng.randint(0, 10) / 100) for _ in range(220)]
    spark.createDataFrame(lines, "l_suppkey long, l_partkey long, l_quantity double, l_discount double").write.parquet(f"{tmp_path}/lineitem.parquet")
    pairs = {}
    for s, p, _, _ in lines:
        if s % 8 != p % 8:
            pairs.setdefault((s % 8, p % 8), set()).add((s, p))
    want = set()
    for (sp, dp), edges in pairs.items():
        sources = sorted({s for s, _ in edges})
        cost = {}  # sources left uncovered put their neighbours into the cover
        for bits in range(1 << len(sources)):
            left = {s for i, s in enumerate(sources) if bits >> i & 1}
            cost[frozenset(left)] = len(sources) - len(left) + len({p for s, p in edges if s in left})
        left = frozenset.intersection(*[x for x, c in cost.items() if c == min(cost.values())])
        want |= {(sp, dp, s, p, "pre" if s in left else "post") for s, p in edges}
    got = [tuple(r) for r in graph_queries.Q["route_edges_lineitem_all"](spark, str(tmp_path)).collect()]
    assert len(got) == len(set(got)) and set(got) == want


def test_codec_computes_its_parameters_once_a_row(spark):
    rows = [(0, 1, "raw", i, 0, [float(x) for x in np.random.default_rng(i).normal(size=16)], 1.0) for i in range(50)] + [(0, 1, "raw", 99, 0, [2.5] * 16, 1.0)]
    sent = spark.createDataFrame(rows, "sp int, dp int, kind string, key long, blk int, v array<double>, n double")
    back = quantize.through(8)(sent)
    # one minimum a row as the zero point and one as the scale's, however the projections are merged
    assert str(back._jdf.queryExecution().optimizedPlan()).count("array_min(v") <= 4
    for r in back.collect():
        v = np.array(dict((x[3], x[5]) for x in rows)[r.key])
        assert np.abs(np.array(r.v) - v).max() <= (v.max() - v.min()) / 255 / 2 + 1e-9


def test_measured_exchange_and_breakdown(spark):
    got = {(r.strategy, r.bits): r for r in training_queries.exchange_time_measured(spark, D, ("turns",)).collect()}
    assert got["hybrid", 32].vectors <= got["best_of_two", 32].vectors <= min(got["pre", 32].vectors, got["post", 32].vectors) <= got["edge", 32].vectors
    assert got["hybrid", 2].shuffle_bytes < got["hybrid", 32].shuffle_bytes
    steps = training_queries.breakdown(spark, D, (("turns", 4),)).collect()
    assert [r.setting for r in steps] == ["base", "optimized"] and steps[0].quantization == 0.0 < steps[1].quantization


def test_delayed_scaling_counts_a_fifth_of_the_plain_bytes(spark):
    got = {(r.parts, r.method): r for r in training_queries.scaling_delayed(spark, D, ("succession",), (4,)).collect()}
    assert got[4, "delayed"].bytes * 5 == pytest.approx(got[4, "plain"].bytes)
    assert got[4, "complete"].bytes < got[4, "plain"].bytes


def test_parts_hold_small_arrays_and_a_state_of_what_is_still_read(spark):
    from dataclasses import replace

    g = tiny(spark)
    held = {}
    for name, edges in (("ones", g.edges), ("weights", g.edges.withColumn("w", F.col("src") + 1.0))):
        rows = train.prepare(graphs.Graph(g.nodes, edges), partition.by_mod(g.nodes, 3), BASE, 3).table.collect()
        held[name] = {p: train.joined({r.seq: bytes(r.payload) for r in rows if r.part == p}) for p in range(3)}
    for p in range(3):
        a, b = held["ones"][p], held["weights"][p]
        assert a["here"][2].dtype == np.int32 and a["here"][3] is None  # edges of weight one carry none
        for one, many in ((a["recv"], b["recv"]), (a["send"], b["send"])):
            assert one.keys() == many.keys()
        for other, r in b["recv"].items():  # an id is its weight less one; sources of a pair are sorted
            sources = [s for s, _ in sorted((s, d) for s, d in [(0, 1), (1, 2), (2, 0), (3, 1), (4, 2), (5, 4), (3, 5), (0, 4), (5, 0)] if s % 3 == other and d % 3 == p)]
            if r["post"][3] is not None:
                assert set(r["post"][3].tolist()) <= {s + 1.0 for s in sources}
    w = train.Worker(train.joined({r.seq: bytes(r.payload) for r in train.prepare(g, partition.by_mod(g.nodes, 1), BASE, 1).table.collect()}), train.init_params(BASE, 3, 2), replace(BASE, dropout=0.5), 0, "train", None)
    for t in range(2 * BASE.layers):
        w.step(t, {})
    assert not w.saved[-1] and not w.new_cache and "hn" not in w.saved[0]
    rows = np.zeros((4, 1))
    train.add_rows(rows, np.array([1, 1, 3]), np.array([[1.0], [2.0], [4.0]]))
    assert rows.ravel().tolist() == [0.0, 3.0, 0.0, 4.0]


def test_word_digests_are_those_of_the_words_and_ids_of_a_gram_are_distinct():
    long = "x" * 40
    texts = ["a b\ta", "", " \n", f"ab {long}y {long}z a\x0bé", "  a\x1cb"]
    digests, doc = graphs._word_digests(texts)
    words = [(i, w) for i, t in enumerate(texts) for w in t.encode().split()]
    assert doc.tolist() == [i for i, _ in words]
    assert len({d.tobytes() for d in digests}) == len({w for _, w in words}) == len({(w, d.tobytes()) for (_, w), d in zip(words, digests)})
    assert all(len(x) == 0 for x in graphs._word_digests([]))
    # two grams with one first half keep apart, and an id counts once for each
    h, g, ids = graphs._distinct(np.array([5, 5, 5, 5], np.uint64), np.array([1, 2, 1, 2], np.uint64), np.array([3, 3, 3, 4]))
    assert list(zip(h.tolist(), g.tolist(), ids.tolist())) == [(5, 1, 3), (5, 2, 3), (5, 2, 4)]


def test_parts_are_the_same_without_joins_and_where_pairs_are_too_large_for_a_task(spark):
    """Edges packed before their routing give the parts of edges routed as rows."""
    nodes = spark.createDataFrame([(i, [float(i), 1.0], i % 2, "train") for i in range(60)] + [(None, [1.0, 1.0], 0, "train")], "id long, feat array<double>, label int, split string")
    ends = sorted({(i, (i + s) % 60) for i in range(60) for s in (1, 3)} | {(i, j) for i in range(0, 20, 5) for j in range(21, 40, 5)} | {(i, i + 1) for i in range(0, 59, 3)})
    assert sum(a % 3 == 0 and b % 3 == 1 for a, b in ends) > 15  # the last case cuts it into components
    for w in (1.0, None):
        edges = spark.createDataFrame([(a, b, w or a + 0.5) for a, b in ends], "src long, dst long, w double")
        g = graphs.Graph(nodes, edges)
        held = []
        for parts, most in ((None, 1000), (partition.by_mod(nodes, 3), 1000), (partition.by_mod(nodes, 3), 15)):
            prep = train.prepare(g, parts, BASE, 3, max_pair_edges=most)
            held.append(sorted((r.part, r.seq, bytes(r.payload)) for r in prep.table.collect()))
            if parts is None:
                assert len(held[0]) == 3
        assert held[0] == held[1] == held[2]


def test_features_of_documents_come_from_arrays(spark, tmp_path):
    """Noise equals the column's; no higher-order function is run for a row."""
    ids = np.array([0, 1, 77, 10_000_003, 1 << 40])
    df = spark.createDataFrame([(int(i),) for i in ids], "id long")
    for k, seed in ((0, 7), (95, 3)):
        assert vectors.uniforms(ids, k, seed).tolist() == [r[0] for r in df.coalesce(1).select(vectors.mix_uniform(F.col("id"), F.lit(k), seed)).collect()]
    texts = ["Ab\u0130 \u03a3\u03a3", "\u00c9t\u00c9 \u4e2d\u6587", "xY" * 700, "z"]
    spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)] + [(None, "ab", "en", "s", 0)], "doc_id long, text string, lang string, source string, n_chars long").coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    g = graphs.shingle_documents(spark, str(tmp_path), 8, noise=0.3)
    assert not any(x in g.nodes._jdf.queryExecution().optimizedPlan().toString() for x in ("lambda", "lower("))
    for r in g.nodes.filter("id is not null").collect():
        t, counts = texts[r.id].lower(), np.zeros(8)
        for a, b in zip(t, t[1:]):
            counts[zlib.crc32((a + b).encode()) % 8] += 1
        normal = [sum(float(vectors.uniforms(np.array([r.id]), k * 12 + j, 7)[0]) for j in range(12)) - 6 for k in range(8)]
        want = counts / np.linalg.norm(counts) + 0.3 * np.array(normal) if len(t) > 1 else np.zeros(8)
        assert np.allclose(r.feat, want), r.id


def test_supersteps_meet_their_messages_without_another_pass(spark):
    """Dealt records keep the serializer of mapped ones, so a union does not write them again; parts stay uncompressed."""
    from pyspark.rdd import PipelinedRDD

    nodes = spark.createDataFrame([(i, [float(i), 1.0], i % 2, "train") for i in range(12)], "id long, feat array<double>, label int, split string")
    edges = spark.createDataFrame([(i, (i + 1) % 12, 1.0) for i in range(12)], "src long, dst long, w double")
    prep = train.prepare(graphs.Graph(nodes, edges), None, BASE, 3)
    dealt = prep.dealt()
    assert not isinstance(dealt, PipelinedRDD) and dealt._jrdd_deserializer == spark.sparkContext.serializer
    assert dealt.getStorageLevel() == train.KEPT and train.KEPT.deserialized
    with train.Epoch(prep, [train.init_params(BASE, 2, 2)], [BASE], 0) as e:
        assert len(e.kept) == 1  # of 2 L + 1 supersteps only the last is still stored
        assert e.totals()[0]["vectors"] > 0
    prep.release()


def test_edges_of_a_fixed_route_are_packed_as_they_are(spark):
    """Marked while they are packed: the parts are those of edges with a column of routes."""
    nodes = spark.createDataFrame([(i, [float(i), 1.0], i % 2, "train") for i in range(30)], "id long, feat array<double>, label int, split string")
    edges = spark.createDataFrame([(i, (i * s + 1) % 30, w) for i in range(30) for s, w in ((1, 1.0), (7, 0.5))], "src long, dst long, w double").dropDuplicates(["src", "dst"])
    located = remote.located_by_mod(edges, 3)
    here, away = remote.split(located)
    for route in ("pre", "post", "edge"):
        rows = remote.plan(away, route).select("sp", "dp", "src", "dst", "w", "route").unionByName(here.select("sp", "dp", "src", "dst", "w", F.lit(None).cast("string").alias("route")))
        flat = lambda df: sorted((r.part, r.kind, r.other or 0, *x) for r in df.collect() for x in zip(np.frombuffer(r.a, np.int64).tolist(), np.frombuffer(r.b, np.int64).tolist(), (np.frombuffer(r.w) if r.w else np.ones(len(r.a) // 8)).tolist(), bytes(r.mark)))
        fast = train._routed(spark, located, route, 1000)
        assert "located" not in "".join(fast.inputFiles())
        assert flat(fast) == flat(rows.mapInArrow(train._pack_edges, train.PACKED))


def test_character_pairs_and_grams_do_not_depend_on_slices(monkeypatch):
    """Pairs are counted 255 at a time in bytes, words hashed in slices: lengths around both, far characters, empty texts."""
    texts = ["", "a", "ab", *("x" * n for n in (255, 256, 257, 511, 512)), "\u65e5a" * 300, "a\u65e5", "\u00e9 \u0130I " * 40, "", "ab cd ab cd ab", "\u65e5"]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(texts)], names=["id", "text"])
    found = {}
    for most in (16, 1 << 16):
        monkeypatch.setattr(graphs, "CHARS", most)
        for buckets in (5, 8, 16):
            rows = pa.Table.from_batches(list(graphs._bigram_counts(buckets)(iter([batch])))).to_pylist()
            want = {}
            for i, t in enumerate(t.lower() for t in texts):
                n = [0] * buckets
                for a, b in zip(t, t[1:]):
                    n[graphs._pair_bucket(ord(a), ord(b), buckets)] += 1
                if any(n):
                    want[i] = n
            assert {r["id"]: [r[f"c{k}"] for k in range(buckets)] for r in rows} == want
        grams = [r for b in graphs._grams(3)(iter([batch])) for r in b.to_pylist()]
        found[most] = sorted((r["bucket"], r["first"], r["second"], r["third"]) for r in grams)
    assert found[16] == found[1 << 16] and len(found[16]) > 0
    assert all(r["bucket"] == h >> 52 for r in grams for h in np.frombuffer(r["first"], np.uint64).tolist())


def test_part_pieces_are_read_in_place(monkeypatch):
    monkeypatch.setattr(train, "CHUNK", 1 << 12)
    value = {"big": np.arange(5000), "some": [np.arange(7, dtype=np.int32), np.zeros(0), np.zeros((0, 3))], "odd": np.arange(11, dtype=np.uint8), "f": np.ones((40, 3)).T, "none": None}
    pieces = train.chunks(value)
    assert all(len(p) <= 1 << 12 for p in pieces[1:])
    back = train.joined(dict(enumerate(pieces)))
    assert np.array_equal(back["big"], value["big"]) and np.array_equal(back["odd"], value["odd"]) and np.array_equal(back["f"], value["f"])
    assert [x.shape for x in back["some"]] == [(7,), (0,), (0, 3)] and back["none"] is None
    # no second copy: the array is a view of the bytes that came with the record
    assert not back["odd"].flags.owndata and not back["odd"].flags.writeable


def test_large_models_take_passes_of_their_own(spark, monkeypatch):
    from dataclasses import replace

    g = tiny(spark)
    cfg = replace(BASE, epochs=2, bits=4, dropout=0.5)
    prep = train.prepare(g, partition.by_mod(g.nodes, 3), cfg, 3)
    assert prep.nodes == g.nodes.count()
    cfgs = [replace(cfg, seed=s, lp=lp) for s in (0, 1) for lp in (False, True)]
    assert train.sharing(prep, cfgs) == [[0, 1, 2, 3]]
    together = train.fit_many(prep, cfgs, eval_every=1)
    monkeypatch.setattr(train, "SHARED_STATE", 1)
    assert train.sharing(prep, cfgs) == [[0], [1], [2], [3]]
    apart = train.fit_many(prep, cfgs, eval_every=1)
    for a, b in zip(together, apart):
        assert [(h["loss"], h["bytes"], h["test_accuracy"]) for h in a.history] == [(h["loss"], h["bytes"], h["test_accuracy"]) for h in b.history]
        assert all(np.array_equal(a.params[k], b.params[k]) for k in a.params)


def test_messages_of_an_epoch_leave_the_disk(spark):
    g = tiny(spark)
    prep = train.prepare(g, partition.by_mod(g.nodes, 3), BASE, 3)
    prep.dealt().count()
    tracker = spark.sparkContext._jsc.sc().env().mapOutputTracker()
    with train.Epoch(prep, [train.init_params(BASE, 3, 2)], [BASE], 0) as e:
        moved = [train._shuffle_of(r) for r in e.moved[:-1]]
        assert len(moved) == 2 * BASE.layers and all(tracker.containsShuffle(i) for i in moved)
        assert e.totals()[0]["stats"]["loss"] > 0
    assert not any(tracker.containsShuffle(i) for i in moved)
    assert train.epoch_total(prep, train.init_params(BASE, 3, 2), BASE, 1)["stats"]["loss"] > 0


def test_sampled_edges_are_the_first_by_hash(spark, monkeypatch):
    rng = np.random.default_rng(3)
    edges = spark.createDataFrame([(int(a) - 20, int(b) - 20, float(a % 3 + 1)) for a, b in {(a, b) for a, b in rng.integers(0, 60, (900, 2)).tolist() if a != b}], "src long, dst long, w double").cache()
    seeds = spark.createDataFrame([(i % 4, i - 20) for i in range(0, 60, 2)], "block int, id long")
    nodes = spark.createDataFrame([(i - 20, [1.0], 0, "train") for i in range(60)], "id long, feat array<double>, label int, split string")
    monkeypatch.setattr(minibatch, "GATHER", 50)
    got_nodes, got = minibatch.sample_blocks(graphs.Graph(nodes, edges), seeds, (3, 2), 7)
    front, taken = seeds, None
    for k, f in enumerate((3, 2)):  # the plain plan: all in-edges of every front node, ranked
        w = Window.partitionBy("block", "dst").orderBy(F.xxhash64("src", "dst", "block", F.lit(700 + k)), "src")
        hop = edges.join(front.select("block", F.col("id").alias("dst")), "dst").withColumn("r", F.row_number().over(w)).filter(F.col("r") <= f).select("block", "src", "dst", "w")
        taken = hop if taken is None else taken.unionByName(hop)
        front = front.unionByName(hop.select("block", F.col("src").alias("id"))).distinct()
    key = lambda df: sorted(tuple(r) for r in df.collect())
    assert key(got) == key(taken.distinct())
    assert key(got_nodes.select("block", "id")) == key(front)


def test_minibatch_groups_give_one_result(spark, monkeypatch):
    from dataclasses import replace

    g = tiny(spark)
    cfg = replace(BASE, epochs=2)
    prep = train.prepare(g, partition.by_mod(g.nodes, 2), cfg, 2)
    whole = minibatch.fit(g, cfg, prep, (3, 2), 4, lanes=2)
    monkeypatch.setattr(minibatch, "GROUP_BYTES", 1)
    monkeypatch.setattr(minibatch, "EDGE_BYTES", 0)
    assert minibatch.updates_together(4, prep.nodes, 100, 3, (3, 2), 9, 2) == 1
    apart = minibatch.fit(g, cfg, prep, (3, 2), 4, lanes=2)
    assert [h["loss"] for h in whole.history] == pytest.approx([h["loss"] for h in apart.history], rel=1e-12)
