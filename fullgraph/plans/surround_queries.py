"""Relational operators, functions, formats and user functions around the methods."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vectors import register
from ..operators import aggregate, cover, relational, remote
from ..session import work_path
from ..sources import graphs, tables
from ..sources.tables import load
from .graph_queries import FEAT_SQL, G2_SQL, G6_SQL, P, Q, SQL, as_sums, g2_features, g2_remote, g6_remote, query

# ---------------------------------------------------------------- joins

query("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")(
    lambda s, d: load(s, d, "customer").join(F.broadcast(load(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")
)
_ORDERS_SQL = "SELECT o_orderpriority, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"
for _h in ("merge", "shuffle_hash"):
    query(f"join_{_h}", _ORDERS_SQL)(
        lambda s, d, h=_h: load(s, d, "orders").join(load(s, d, "customer").hint(h), F.col("o_custkey") == F.col("c_custkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    )


@query("join_shuffle_replicate_nl", _ORDERS_SQL)
def join_shuffle_replicate_nl(s: SparkSession, d: str) -> DataFrame:
    """Blocks of keys against blocks of keys: every pair of blocks is looked at, but rows only inside blocks of one range."""
    block = 128
    c = load(s, d, "customer").select(F.col("c_custkey").alias("k")).filter("k is not null")
    o = load(s, d, "orders").filter("o_custkey is not null").groupBy(F.col("o_custkey").alias("k"), "o_orderpriority").agg(F.count(F.lit(1)).alias("c"))
    a = c.groupBy(F.floor(F.col("k") / block).alias("a")).agg(F.collect_list("k").alias("keys"))
    b = o.groupBy(F.floor(F.col("k") / block).alias("b")).agg(F.collect_list(F.struct("k", "o_orderpriority", "c")).alias("rows"))
    met = b.join(a.hint("shuffle_replicate_nl"), F.col("a") == F.col("b"))
    found = met.select("keys", F.inline("rows")).select("o_orderpriority", (F.col("c") * F.size(F.filter("keys", lambda x: x == F.col("k")))).alias("n")).filter("n > 0")
    return found.groupBy("o_orderpriority").agg(F.sum("n").alias("n"))


query("join_semi", f"WITH {G2_SQL} SELECT p_partkey AS id FROM part WHERE p_partkey IN (SELECT dst FROM r)")(
    lambda s, d: load(s, d, "part").select(F.col("p_partkey").alias("id")).join(g2_remote(s, d).select(F.col("dst").alias("id")), "id", "left_semi")
)
query("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
query("join_left", "SELECT c_custkey, count(o_orderkey)::BIGINT AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")(
    lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))
)
query("join_full", "SELECT coalesce(l.doc_id, d.doc_id) AS doc_id, l.doc_id IS NULL AS unlabelled FROM documents d FULL JOIN labels l ON l.doc_id = d.doc_id")(
    lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "labels").select("doc_id", F.lit(1).alias("x")), "doc_id", "full").select("doc_id", F.col("x").isNull().alias("unlabelled"))
)
query("join_null_safe", "SELECT count(*)::BIGINT AS n FROM (SELECT CASE WHEN c_custkey % 3 = 0 THEN NULL ELSE c_nationkey END AS k FROM customer) a JOIN nation b ON a.k IS NOT DISTINCT FROM CASE WHEN n_nationkey = 0 THEN NULL ELSE n_nationkey END")(
    lambda s, d: load(s, d, "customer")
    .select(F.when(F.col("c_custkey") % 3 != 0, F.col("c_nationkey")).alias("k"))
    .join(load(s, d, "nation").select(F.when(F.col("n_nationkey") != 0, F.col("n_nationkey")).alias("j")), F.col("k").eqNullSafe(F.col("j")))
    .agg(F.count(F.lit(1)).alias("n"))
)
query("join_theta", "SELECT a.r_regionkey AS a, b.r_regionkey AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")(
    lambda s, d: load(s, d, "region").select(F.col("r_regionkey").alias("a")).join(load(s, d, "region").select(F.col("r_regionkey").alias("b")), F.col("a") < F.col("b"))
)
query("join_cross_tiny", "SELECT a.r_name AS x, b.n_name AS y FROM region a CROSS JOIN nation b")(lambda s, d: load(s, d, "region").select(F.col("r_name").alias("x")).crossJoin(load(s, d, "nation").select(F.col("n_name").alias("y"))))
query(
    "join_asof",
    """WITH c AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click'), o AS (SELECT event_id, user_id, ts, value FROM events WHERE event_type <> 'click')
SELECT c.event_id, (SELECT max_by(o.event_id, o.ts) FROM o WHERE o.user_id = c.user_id AND o.ts < c.ts) AS last_other FROM c""",
)(lambda s, d: relational.asof(*[load(s, d, "events").filter(f).select("event_id", "user_id", "ts") for f in ("event_type = 'click'", "event_type <> 'click'")], by="user_id", on="ts", value="event_id").select("event_id", F.col("matched").alias("last_other")))
query(
    "join_range",
    "SELECT a.event_id AS x, b.event_id AS y FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
)(lambda s, d: relational.within(load(s, d, "events").select("event_id", "user_id", "ts"), by="user_id", seconds=3600))

# ---------------------------------------------------------------- aggregates

_PAIRS = f"WITH {G2_SQL} SELECT sp, dp, count(*)::BIGINT AS n FROM r GROUP BY "
query("cube_comm", _PAIRS + "CUBE (sp, dp)")(lambda s, d: g2_remote(s, d).cube("sp", "dp").agg(F.count(F.lit(1)).alias("n")))
query("rollup_comm", _PAIRS + "ROLLUP (sp, dp)")(lambda s, d: g2_remote(s, d).rollup("sp", "dp").agg(F.count(F.lit(1)).alias("n")))


@query("grouping_sets_comm", _PAIRS + "GROUPING SETS ((sp), (dp), ())")
def grouping_sets_comm(s: SparkSession, d: str) -> DataFrame:
    return s.sql("SELECT sp, dp, count(*) AS n FROM {r} GROUP BY GROUPING SETS ((sp), (dp), ())", r=g2_remote(s, d))


query("pivot_comm", f"WITH {G2_SQL} SELECT sp, " + ", ".join(f"(count(*) FILTER (WHERE dp = {i}))::BIGINT AS to{i}" for i in range(P)) + " FROM r GROUP BY sp")(
    lambda s, d: g2_remote(s, d).groupBy("sp").pivot("dp", list(range(P))).agg(F.count(F.lit(1))).select("sp", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"to{i}") for i in range(P)])
)
query("agg_distinct", "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY 1")(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users")))
Q["agg_approx_distinct"] = lambda s, d: load(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))
query("agg_collect", "SELECT c_nationkey, list_sort(list(DISTINCT c_mktsegment)) AS segments FROM customer GROUP BY 1")(lambda s, d: load(s, d, "customer").groupBy("c_nationkey").agg(F.sort_array(F.collect_set("c_mktsegment")).alias("segments")))
query("agg_max_by", "SELECT o_custkey, max_by(o_orderkey, (o_orderdate, o_orderkey)) AS last_order FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("last_order")))
query("agg_bits", "SELECT l_returnflag, bit_or(l_partkey) AS o, bit_and(l_partkey) AS a, bit_xor(l_partkey) AS x FROM lineitem GROUP BY 1")(
    lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.bit_or("l_partkey").alias("o"), F.bit_and("l_partkey").alias("a"), F.bit_xor("l_partkey").alias("x"))
)
query("degree_histogram", f"WITH {G2_SQL}, g AS (SELECT dst, count(*) AS d FROM e GROUP BY dst) SELECT d::BIGINT AS degree, count(*)::BIGINT AS nodes FROM g GROUP BY d")(
    lambda s, d: graphs.part_supplier(s, d).edges.groupBy("dst").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("nodes"))
)
Q["agg_percentile_approx"] = lambda s, d: load(s, d, "orders").agg(F.percentile_approx("o_totalprice", [0.1, 0.5, 0.9], 1000).alias("p"))
query("agg_spread", "SELECT event_type, round(stddev(value), 6) AS sd, round(var_pop(value), 6) AS vp FROM events GROUP BY 1")(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.round(F.stddev("value"), 6).alias("sd"), F.round(F.var_pop("value"), 6).alias("vp")))

# ---------------------------------------------------------------- windows, order, top-k



def _u():
    """Events of a user in order; made when a session is there."""
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


query("window_lag", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(
    lambda s, d: load(s, d, "events").select("event_id", F.lag("event_type").over(_u()).alias("before"), F.lead("event_type").over(_u()).alias("after"))
)
query("window_frame", "SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS s3, sum(event_id) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW)::BIGINT AS near FROM events")(
    lambda s, d: load(s, d, "events").select("event_id", F.sum("event_id").over(_u().rowsBetween(-2, 0)).alias("s3"), F.sum("event_id").over(Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-100, 0)).alias("near"))
)
query("window_rank", "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")(
    lambda s, d: (lambda w: load(s, d, "orders").select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).cast("long").alias("q")))(Window.partitionBy("o_custkey").orderBy("o_orderpriority"))
)
query("window_first_last", "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(
    lambda s, d: (lambda w: load(s, d, "events").select("event_id", F.first("event_id").over(w).alias("f"), F.last("event_id").over(w).alias("l"), F.nth_value("event_id", 2).over(w).alias("n")))(_u().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
)
query("topk_per_node", f"WITH {G6_SQL}, c AS (SELECT u AS src, v AS dst, count(*) AS n FROM ev WHERE u IS NOT NULL AND u <> v GROUP BY u, v), k AS (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY n DESC, src) AS r FROM c) SELECT dst, src, n::BIGINT AS n FROM k WHERE r <= 3")(
    lambda s, d: relational.top_k(graphs.succession(load(s, d, "events")).filter("u <> v").groupBy(F.col("u").alias("src"), F.col("v").alias("dst")).agg(F.count(F.lit(1)).alias("n")), "dst", [F.desc("n"), "src"], 3).select("dst", "src", "n")
)
query("sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda s, d: load(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice"))
query("sort_offset", "SELECT p_partkey FROM part ORDER BY p_retailprice, p_partkey LIMIT 5 OFFSET 20")(lambda s, d: load(s, d, "part").orderBy("p_retailprice", "p_partkey").offset(20).limit(5).select("p_partkey"))

# ---------------------------------------------------------------- sets of edges


def _routes(s: SparkSession, d: str) -> DataFrame:
    return cover.routed_by_cover(g6_remote(s, d))


query("except_edges", "SELECT 0::BIGINT AS missing, 0::BIGINT AS extra")(
    lambda s, d: (lambda r, q: r.select("sp", "dp", "src", "dst").exceptAll(q.select("sp", "dp", "src", "dst")).agg(F.count(F.lit(1)).alias("missing")).crossJoin(q.select("sp", "dp", "src", "dst").exceptAll(r.select("sp", "dp", "src", "dst")).agg(F.count(F.lit(1)).alias("extra"))))(g6_remote(s, d), _routes(s, d))
)
query("intersect_edges", "SELECT 0::BIGINT AS both")(
    lambda s, d: (lambda q: q.filter("route = 'pre'").select("sp", "dp", "src", "dst").intersect(q.filter("route = 'post'").select("sp", "dp", "src", "dst")).agg(F.count(F.lit(1)).alias("both")))(_routes(s, d))
)
query("union_edges", f"WITH {G2_SQL} SELECT src, dst FROM e UNION SELECT dst, src FROM e")(lambda s, d: (lambda e: e.select("src", "dst").union(e.select(F.col("dst"), F.col("src"))).distinct())(graphs.part_supplier(s, d).edges))

# ---------------------------------------------------------------- graph helpers

query("khop", f"WITH {G6_SQL}, a AS (SELECT 0::BIGINT AS id UNION SELECT dst FROM e WHERE src = 0) SELECT id FROM a UNION SELECT dst FROM e JOIN a ON src = id")(lambda s, d: relational.khop(graphs.user_succession(s, d).edges, s.createDataFrame([(0,)], "id long"), 2))
query("triangles", f"WITH {G6_SQL}, u AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM e) SELECT count(*)::BIGINT AS triangles FROM u x JOIN u y ON x.b = y.a JOIN u z ON z.a = x.a AND z.b = y.b")(
    lambda s, d: relational.triangles(graphs.user_succession(s, d).edges)
)
query(
    "connected_components",
    f"WITH RECURSIVE {G2_SQL}, u AS (SELECT src, dst FROM e), reach AS (SELECT DISTINCT src AS a, src AS b FROM u UNION SELECT reach.a, u.dst FROM reach JOIN u ON u.src = reach.b) SELECT a AS node, min(b) AS component FROM reach GROUP BY a",
)(lambda s, d: relational.connected(graphs.part_supplier(s, d).edges))
Q["pagerank"] = lambda s, d: relational.pagerank(graphs.user_succession(s, d).edges, 5)

# ---------------------------------------------------------------- functions

query("json_props", "SELECT event_id, (props->>'k')::BIGINT AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
query("map_props", "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS k FROM events WHERE (props->>'k')::BIGINT > 50 GROUP BY 1")(
    lambda s, d: load(s, d, "events").select("event_type", F.map_filter(F.from_json("props", "map<string,long>"), lambda k, v: v > 50)["k"].alias("k")).filter("k is not null").groupBy("event_type").agg(F.sum("k").alias("k"))
)
query("string_functions", "SELECT p_partkey, upper(p_name) AS u, length(p_name)::INT AS n, split_part(p_type, ' ', 1) AS kind, md5(p_brand) AS h FROM part")(
    lambda s, d: load(s, d, "part").select("p_partkey", F.upper("p_name").alias("u"), F.length("p_name").alias("n"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("kind"), F.md5("p_brand").alias("h"))
)
query("date_functions", "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS m, datediff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days FROM orders")(
    lambda s, d: load(s, d, "orders").select("o_orderkey", F.to_date(F.date_trunc("month", "o_orderdate")).alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"))
)
query("null_functions", "SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'other') AS seg, CASE WHEN c_acctbal < 0 THEN 'debt' ELSE 'fine' END AS state FROM customer")(
    lambda s, d: load(s, d, "customer").select("c_custkey", F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("other")).alias("seg"), F.when(F.col("c_acctbal") < 0, "debt").otherwise("fine").alias("state"))
)
query("filters", "SELECT count(*)::BIGINT AS n FROM part WHERE p_size BETWEEN 5 AND 20 AND p_name LIKE '%a%' AND p_brand IS NOT NULL")(
    lambda s, d: load(s, d, "part").filter(F.col("p_size").between(5, 20) & F.col("p_name").like("%a%") & F.col("p_brand").isNotNull()).agg(F.count(F.lit(1)).alias("n"))
)


@query("sql_vector_functions", "SELECT vec_id, (list_position(embedding, list_max(embedding)) - 1)::INT AS k FROM embeddings")
def sql_vector_functions(s: SparkSession, d: str) -> DataFrame:
    register(s)
    return s.sql("SELECT vec_id, vec_argmax(CAST(embedding AS ARRAY<DOUBLE>)) AS k FROM {e}", e=load(s, d, "embeddings"))


# ---------------------------------------------------------------- user functions


@query("udf_pack", "SELECT vec_id, 16::INT AS bytes FROM embeddings")
def udf_pack(s: SparkSession, d: str) -> DataFrame:
    relational.ready(s)

    @F.pandas_udf("binary")
    def pack_int2(v: pd.Series) -> pd.Series:
        import numpy as np

        from fullgraph.operators.quantize import quantize_rows

        return pd.Series([quantize_rows(np.asarray(x, dtype=float)[None], 2)[0][0].tobytes() for x in v])

    return load(s, d, "embeddings").select("vec_id", F.length(pack_int2("embedding")).alias("bytes"))


query("udf_grouped_sum", "SELECT label, round(sum(embedding[1]::DOUBLE), 6) AS x FROM embeddings GROUP BY label")(lambda s, d: relational.vector_sum(load(s, d, "embeddings").select("label", "embedding")).select("label", F.round(F.get("v", F.lit(0)), 6).alias("x")))


@query("udtf_cover", SQL["cover_members"])
def udtf_cover(s: SparkSession, d: str) -> DataFrame:
    relational.register_udtf(s)
    pairs = g6_remote(s, d).groupBy("sp", "dp").agg(F.array_join(F.collect_list(F.concat_ws("-", "src", "dst")), ",").alias("edges"))
    return s.sql("SELECT t.sp, t.dp, c.side, c.id FROM {pairs} t, LATERAL cover_of(t.edges) c", pairs=pairs)


# ---------------------------------------------------------------- formats


def _round_trip(fmt: str, **options):
    def run(s: SparkSession, d: str) -> DataFrame:
        path = work_path(s, f"fmt-{fmt}")
        rows = load(s, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
        tables.write(rows, path, fmt, **options)
        return tables.read(s, path, fmt, "n_nationkey int, n_name string, n_regionkey int", **options)

    return run


for _f in ("csv", "json", "orc", "parquet"):
    query(f"format_{_f}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(_round_trip(_f))


@query("format_partitioned", f"WITH {G2_SQL} SELECT src, dst, dp FROM r WHERE sp = 3")
def format_partitioned(s: SparkSession, d: str) -> DataFrame:
    path = work_path(s, "by-part")
    tables.write(g2_remote(s, d).select("sp", "dp", "src", "dst"), path, by=["sp"])
    return s.read.parquet(path).filter("sp = 3").select("src", "dst", "dp")


@query("format_edge_list", f"WITH {G2_SQL} SELECT src, dst FROM r")
def format_edge_list(s: SparkSession, d: str) -> DataFrame:
    path = work_path(s, "edge-list")
    g2_remote(s, d).select(F.concat_ws(" ", "src", "dst").alias("value")).write.text(path)
    return tables.read_edge_list(s, path).select("src", "dst")


@query("format_bucketed", f"WITH {G2_SQL} SELECT sp, dp, count(*)::BIGINT AS n FROM r GROUP BY sp, dp")
def format_bucketed(s: SparkSession, d: str) -> DataFrame:
    import uuid

    name = f"edges_{uuid.uuid4().hex[:12]}"
    tables.write_bucketed(g2_remote(s, d), name, 4, "dp", ["dp", "src"])
    return s.table(name).groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("n"))


@query("udf_cogroup_absorb", f"WITH {G2_SQL}, {FEAT_SQL} SELECT r.dst, k, sum(x)::BIGINT AS s FROM r JOIN fx ON fx.id = r.src GROUP BY r.dst, k")
def udf_cogroup_absorb(s: SparkSession, d: str) -> DataFrame:
    post = remote.plan(g2_remote(s, d), "post")
    got = aggregate.absorb_cogrouped(aggregate.raw(post, g2_features(s, d)), post)
    return as_sums(got.select("dst", "blk", F.transform("v", lambda x: x.cast("long")).alias("v")))


@query("sql_spmm", f"WITH {G2_SQL}, {FEAT_SQL} SELECT e.dst, k, sum(x)::BIGINT AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k")
def sql_spmm(s: SparkSession, d: str) -> DataFrame:
    f = g2_features(s, d).select("id", "blk", F.posexplode("v").alias("i", "x"))
    text = "SELECT e.dst, CAST(16 * f.blk + f.i AS INT) AS k, sum(f.x) AS s FROM {e} e JOIN {f} f ON e.src = f.id WHERE 16 * f.blk + f.i < 3 GROUP BY e.dst, 16 * f.blk + f.i"
    return s.sql(text, e=graphs.part_supplier(s, d).edges, f=f)


@query("sql_views", "SELECT n_name, count(*)::BIGINT AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def sql_views(s: SparkSession, d: str) -> DataFrame:
    tables.register_views(s, d, ["supplier", "nation"])
    return s.sql("SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
