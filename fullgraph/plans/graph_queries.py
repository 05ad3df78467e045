"""Graphs, splits, volumes, covers, aggregation, quantization, cost: queries that SQL can check."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import fixed_point, from_block, mix_uniform, mix_uniform_sql, to_block, to_long
from ..operators import aggregate, costmodel, cover, layers, metrics, partition, propagate, quantize, remote
from ..session import cut
from ..sources import graphs
from ..sources.tables import load

P = 8
SUCC_P = 16
Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# ---------------------------------------------------------------- SQL pieces

G2_SQL = """pairs AS (SELECT DISTINCT l_partkey AS p, l_suppkey + 10000000 AS s FROM lineitem WHERE l_quantity >= 40 AND l_discount >= 0.08),
e AS (SELECT p AS src, s AS dst FROM pairs UNION ALL SELECT s, p FROM pairs),
el AS (SELECT (src % 8)::INT AS sp, (dst % 8)::INT AS dp, src, dst FROM e),
r AS (SELECT * FROM el WHERE sp <> dp)"""
G6_SQL = """ev AS (SELECT user_id AS v, lag(user_id) OVER (ORDER BY ts, event_id) AS u FROM events),
e AS (SELECT u AS src, v AS dst FROM ev WHERE u IS NOT NULL AND u <> v GROUP BY u, v HAVING count(*) >= 2),
el AS (SELECT (src % 16)::INT AS sp, (dst % 16)::INT AS dp, src, dst FROM e),
r AS (SELECT * FROM el WHERE sp <> dp)"""
FEAT_SQL = """f AS (SELECT p_partkey AS id, [1.0::DOUBLE, p_size / 50.0::DOUBLE, p_retailprice / 2000.0::DOUBLE] AS v FROM part
UNION ALL SELECT s_suppkey + 10000000, [0.0::DOUBLE, s_nationkey / 25.0::DOUBLE, s_acctbal / 10000.0::DOUBLE] FROM supplier),
fx AS (SELECT id, k::INT AS k, CAST(floor(v[k + 1] * 1048576) AS BIGINT) AS x FROM f, range(3) AS t(k))"""

# The source side is enumerated: a subset S left uncovered costs |U| - |S| + |N(S)|; the intersection of
# the best subsets holds exactly the sources outside the canonical cover.
def bitmask_sql(edges: str) -> str:
    return f"""uu AS (SELECT sp, dp, src, row_number() OVER (PARTITION BY sp, dp ORDER BY src) - 1 AS ui FROM (SELECT DISTINCT sp, dp, src FROM {edges})),
vv AS (SELECT sp, dp, dst, row_number() OVER (PARTITION BY sp, dp ORDER BY dst) - 1 AS vi FROM (SELECT DISTINCT sp, dp, dst FROM {edges})),
adj AS (SELECT uu.sp, uu.dp, ui, bit_or(1::HUGEINT << vi::INT) AS m FROM {edges} x JOIN uu ON uu.sp = x.sp AND uu.dp = x.dp AND uu.src = x.src
  JOIN vv ON vv.sp = x.sp AND vv.dp = x.dp AND vv.dst = x.dst GROUP BY uu.sp, uu.dp, ui),
nu AS (SELECT sp, dp, count(*)::INT AS n FROM uu GROUP BY sp, dp),
subsets AS (SELECT sp, dp, n, unnest(range((1 << n)::BIGINT)) AS s FROM nu),
cost AS (SELECT subsets.sp, subsets.dp, s, any_value(n) - bit_count(s) + coalesce(bit_count(bit_or(m)), 0) AS c
  FROM subsets LEFT JOIN adj ON adj.sp = subsets.sp AND adj.dp = subsets.dp AND ((s >> ui) & 1) = 1 GROUP BY subsets.sp, subsets.dp, s),
best AS (SELECT sp, dp, min(c)::BIGINT AS size FROM cost GROUP BY sp, dp),
open AS (SELECT cost.sp, cost.dp, bit_and(s) AS s, any_value(size) AS size FROM cost JOIN best ON cost.sp = best.sp AND cost.dp = best.dp AND c = size GROUP BY cost.sp, cost.dp),
routed AS (SELECT x.sp, x.dp, x.src, x.dst, CASE WHEN ((open.s >> uu.ui) & 1) = 1 THEN 'pre' ELSE 'post' END AS route
  FROM {edges} x JOIN uu ON uu.sp = x.sp AND uu.dp = x.dp AND uu.src = x.src JOIN open ON open.sp = x.sp AND open.dp = x.dp)"""


LINES_SQL = """r AS (SELECT DISTINCT (l_suppkey % 8)::INT AS sp, (l_partkey % 8)::INT AS dp, l_suppkey AS src, l_partkey AS dst
  FROM lineitem WHERE l_quantity >= 45 AND l_discount >= 0.09 AND l_suppkey % 8 <> l_partkey % 8)"""


# ---------------------------------------------------------------- inputs

def g2_located(spark: SparkSession, d: str) -> DataFrame:
    return remote.located_by_mod(graphs.part_supplier(spark, d).edges, P)


def g2_remote(spark: SparkSession, d: str) -> DataFrame:
    return remote.split(g2_located(spark, d))[1]


def g6_remote(spark: SparkSession, d: str) -> DataFrame:
    return remote.split(remote.located_by_mod(graphs.user_succession(spark, d).edges, SUCC_P))[1]


def lines_remote(spark: SparkSession, d: str, keep: str = "l_quantity >= 45 and l_discount >= 0.09") -> DataFrame:
    li = load(spark, d, "lineitem").filter(keep)
    e = li.select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"), F.lit(1.0).alias("w")).distinct()
    return remote.split(remote.located_by_mod(e, P))[1]


def g2_features(spark: SparkSession, d: str) -> DataFrame:
    """Three attributes per node, as whole numbers at scale 2^20, in blocks."""
    p = load(spark, d, "part").select(F.col("p_partkey").alias("id"), F.array(F.lit(1.0), F.col("p_size") / 50.0, F.col("p_retailprice") / 2000.0).alias("v"))
    s = load(spark, d, "supplier").select((F.col("s_suppkey") + graphs.SECOND).alias("id"), F.array(F.lit(0.0), F.col("s_nationkey") / 25.0, F.col("s_acctbal") / 10000.0).alias("v"))
    v = p.unionByName(s).select("id", F.transform("v", fixed_point).alias("v"))
    return to_block(v)


def as_sums(blocks: DataFrame, width: int = 3, key: str = "dst") -> DataFrame:
    out = blocks.select(F.col(key).alias("dst"), F.col("blk"), F.posexplode("v").alias("i", "s"))
    return out.select("dst", (F.col("blk") * 16 + F.col("i")).cast("int").alias("k"), F.col("s").cast("long").alias("s")).filter(F.col("k") < width)


# ---------------------------------------------------------------- graphs

def _edge_query(name: str, build, sql: str) -> None:
    query(name, sql)(lambda spark, d: build(spark, d).edges.select("src", "dst"))


_edge_query("g_copurchase_edges", graphs.copurchase_parts, "SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey")
_edge_query("g_part_supplier_edges", graphs.part_supplier, f"WITH {G2_SQL} SELECT src, dst FROM e")
_edge_query(
    "g_doc_shingle_edges",
    graphs.shingle_documents,
    r"""WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(ws[i + 1 : i + 3], ' ') AS gram FROM (SELECT doc_id, ws, unnest(range(len(ws) - 2)) AS i FROM w WHERE len(ws) >= 3)),
h AS (SELECT gram FROM g GROUP BY gram HAVING count(*) BETWEEN 2 AND 10), k AS (SELECT g.* FROM g JOIN h ON g.gram = h.gram)
SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM k a JOIN k b ON a.gram = b.gram AND a.doc_id <> b.doc_id""",
)
_edge_query(
    "g_page_links",
    graphs.page_links,
    """WITH h AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(coalesce(html, ''), 'href="([^"]*)"', 1)) AS target FROM pages),
t AS (SELECT target, dense_rank() OVER (ORDER BY target) - 1 + 10000000 AS tid FROM (SELECT DISTINCT target FROM h)),
l AS (SELECT page_id AS src, tid AS dst FROM h JOIN t ON h.target = t.target) SELECT src, dst FROM l UNION ALL SELECT dst, src FROM l""",
)
_edge_query("g_user_succession", graphs.user_succession, f"WITH {G6_SQL} SELECT src, dst FROM e")
_edge_query("g_turns", graphs.conversation_turns, "WITH c AS (SELECT DISTINCT conv_id * 1000 + turn AS id FROM conversations) SELECT a.id AS src, b.id AS dst FROM c a JOIN c b ON b.id = a.id + 1 WHERE b.id % 1000 <> 0")
_edge_query(
    "g_customer_part",
    graphs.customer_part,
    "WITH p AS (SELECT DISTINCT o_custkey + 10000000 AS c, l_partkey AS p FROM lineitem JOIN orders ON l_orderkey = o_orderkey) SELECT c AS src, p AS dst FROM p UNION ALL SELECT p, c FROM p",
)
query(
    "g_knn_topk",
    "WITH s AS (SELECT a.vec_id AS dst, b.vec_id AS src, list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS s FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) SELECT src, dst FROM s QUALIFY row_number() OVER (PARTITION BY dst ORDER BY s DESC, src) <= 10",
)(lambda spark, d: graphs.knn_embeddings(spark, d).edges.select("src", "dst"))
query("g_symmetrize", f"WITH {G6_SQL} SELECT src, dst FROM e UNION SELECT dst, src FROM e")(lambda spark, d: graphs.symmetrize(graphs.user_succession(spark, d).edges).select("src", "dst"))
query(
    "g_project_parts",
    """WITH b AS (SELECT DISTINCT l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_quantity >= 40 AND l_discount >= 0.08)
SELECT DISTINCT a.p AS src, c.p AS dst FROM b a JOIN b c ON a.s = c.s AND a.p <> c.p""",
)(lambda spark, d: graphs.project(graphs.part_supplier(spark, d).edges.filter(F.col("dst") >= graphs.SECOND)).select("src", "dst"))
query("g_degree", f"WITH {G6_SQL}, i AS (SELECT dst AS id, count(*) AS a FROM e GROUP BY dst), o AS (SELECT src AS id, count(*) AS b FROM e GROUP BY src) SELECT coalesce(i.id, o.id) AS id, coalesce(a, 0)::BIGINT AS in_degree, coalesce(b, 0)::BIGINT AS out_degree FROM i FULL JOIN o ON i.id = o.id")(
    lambda spark, d: graphs.degree(graphs.user_succession(spark, d).edges)
)
query(
    "g_node_weights",
    f"WITH {G2_SQL}, n AS (SELECT p_partkey AS id FROM part UNION ALL SELECT s_suppkey + 10000000 FROM supplier), g AS (SELECT dst, count(*) AS c FROM e GROUP BY dst) SELECT id, (coalesce(c, 0) + CASE WHEN id % 10 <= 4 THEN 1 ELSE 0 END)::DOUBLE AS weight FROM n LEFT JOIN g ON g.dst = n.id",
)(lambda spark, d: (lambda g: partition.node_weights(g.nodes, g.edges))(graphs.part_supplier(spark, d)))

# ---------------------------------------------------------------- split

query("split_local_remote", f"WITH {G2_SQL} SELECT sp, dp, sp <> dp AS is_remote, count(*)::BIGINT AS edges FROM el GROUP BY sp, dp")(
    lambda spark, d: g2_located(spark, d).groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("edges")).select("sp", "dp", (F.col("sp") != F.col("dp")).alias("is_remote"), "edges")
)
query("boundary_nodes", f"WITH {G2_SQL} SELECT DISTINCT src, sp, dp FROM r")(lambda spark, d: remote.boundary(g2_remote(spark, d)))
query("inner_nodes", f"WITH {G2_SQL}, n AS (SELECT p_partkey AS id FROM part UNION ALL SELECT s_suppkey + 10000000 FROM supplier) SELECT id FROM n WHERE id NOT IN (SELECT dst FROM r)")(
    lambda spark, d: remote.inner(graphs.part_supplier(spark, d).nodes, g2_remote(spark, d)).select("id")
)
query("partition_quality", f"WITH {G2_SQL}, p AS (SELECT sp, dp, count(*) AS e FROM el GROUP BY sp, dp) SELECT sum(e)::BIGINT AS edges, (sum(e) FILTER (WHERE sp <> dp))::BIGINT AS cut_edges, ((sum(e) FILTER (WHERE sp <> dp)) / sum(e))::DOUBLE AS cut_ratio, (max(e) FILTER (WHERE sp <> dp))::BIGINT AS busiest_pair FROM p")(
    lambda spark, d: metrics.partition_quality(g2_located(spark, d))
)


@query(
    "cut_by_region_rollup",
    """WITH o AS (SELECT DISTINCT c_nationkey AS a, s_nationkey AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey)
SELECT x.n_regionkey AS from_region, y.n_regionkey AS to_region, count(*)::BIGINT AS pairs FROM o JOIN nation x ON x.n_nationkey = a JOIN nation y ON y.n_nationkey = b WHERE a <> b GROUP BY ROLLUP (x.n_regionkey, y.n_regionkey)""",
)
def cut_by_region_rollup(spark: SparkSession, d: str) -> DataFrame:
    t = {n: load(spark, d, n) for n in ("lineitem", "orders", "customer", "supplier", "nation")}
    j = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("c_custkey") == F.col("o_custkey")).join(t["supplier"], F.col("s_suppkey") == F.col("l_suppkey"))
    pairs = j.select(F.col("c_nationkey").alias("a"), F.col("s_nationkey").alias("b")).distinct().filter("a <> b")
    at = lambda c, name: t["nation"].select(F.col("n_nationkey").alias(c), F.col("n_regionkey").alias(name))
    return pairs.join(at("a", "from_region"), "a").join(at("b", "to_region"), "b").rollup("from_region", "to_region").agg(F.count(F.lit(1)).alias("pairs"))


# ---------------------------------------------------------------- strategies

for _s, _k in (("edge", "count(*)"), ("pre", "count(DISTINCT dst)"), ("post", "count(DISTINCT src)"), ("best_of_two", "least(count(DISTINCT dst), count(DISTINCT src))")):
    query(f"volume_{_s}", f"WITH {G2_SQL} SELECT sp, dp, ({_k})::BIGINT AS vectors FROM r GROUP BY sp, dp")(
        lambda spark, d, c="edges" if _s == "edge" else _s: remote.volumes(g2_remote(spark, d)).select("sp", "dp", F.col(c).alias("vectors"))
    )


def _g6_routed(spark: SparkSession, d: str) -> DataFrame:
    return cover.routed_by_cover(g6_remote(spark, d))


BIT6 = f"WITH {G6_SQL}, {bitmask_sql('r')}"
query("volume_hybrid", f"{BIT6} SELECT sp, dp, size AS vectors FROM open")(lambda spark, d: remote.shipped(_g6_routed(spark, d)))
query("route_edges", f"{BIT6} SELECT sp, dp, src, dst, route FROM routed")(lambda spark, d: _g6_routed(spark, d).select("sp", "dp", "src", "dst", "route"))
query("cover_members", f"{BIT6} SELECT DISTINCT sp, dp, 'src' AS side, src AS id FROM routed WHERE route = 'post' UNION ALL SELECT DISTINCT sp, dp, 'dst', dst FROM routed WHERE route = 'pre'")(lambda spark, d: cover.minimum_cover(g6_remote(spark, d)))
query("matching_size", f"{BIT6} SELECT sp, dp, size AS matched FROM open")(lambda spark, d: cover.matching_sizes(g6_remote(spark, d)))
query("route_edges_lineitem", f"WITH {LINES_SQL}, {bitmask_sql('r')} SELECT sp, dp, src, dst, route FROM routed")(lambda spark, d: cover.routed_by_cover(lines_remote(spark, d)).select("sp", "dp", "src", "dst", "route"))
# the whole table; its pairs are too wide for the bitmasks of the SQL above
Q["route_edges_lineitem_all"] = lambda spark, d: cover.routed_by_cover(lines_remote(spark, d, "true")).select("sp", "dp", "src", "dst", "route")
query(
    "cover_components",
    f"""WITH RECURSIVE {G6_SQL}, two AS (SELECT DISTINCT x.sp, x.dp, x.src AS a, y.src AS b FROM r x JOIN r y ON x.sp = y.sp AND x.dp = y.dp AND x.dst = y.dst),
reach AS (SELECT DISTINCT sp, dp, src AS a, src AS b FROM r UNION SELECT reach.sp, reach.dp, reach.a, two.b FROM reach JOIN two ON two.sp = reach.sp AND two.dp = reach.dp AND two.a = reach.b),
low AS (SELECT sp, dp, a, min(b) AS component FROM reach GROUP BY sp, dp, a)
SELECT r.sp, r.dp, r.src, r.dst, component FROM r JOIN low ON low.sp = r.sp AND low.dp = r.dp AND low.a = r.src""",
)(lambda spark, d: cover.components(g6_remote(spark, d)).select("sp", "dp", "src", "dst", "component"))


def worked_edges(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(1, 0, 4, 1), (1, 0, 4, 2), (1, 0, 4, 3), (1, 0, 5, 2), (1, 0, 6, 2)], "sp int, dp int, src long, dst long").withColumn("w", F.lit(1.0))


@query(
    "worked_example",
    f"{BIT6}, v AS (SELECT count(*) AS a, count(DISTINCT dst) AS b, count(DISTINCT src) AS c FROM r GROUP BY sp, dp) SELECT 'edge' AS strategy, sum(a)::BIGINT AS vectors FROM v UNION ALL SELECT 'pre', sum(b)::BIGINT FROM v UNION ALL SELECT 'post', sum(c)::BIGINT FROM v UNION ALL SELECT 'hybrid', sum(size)::BIGINT FROM open",
)
def worked_example(spark: SparkSession, d: str) -> DataFrame:
    """Vectors by strategy on the users' graph."""
    return strategy_vectors(cut(spark, g6_remote(spark, d), "remote"))


def strategy_vectors(e: DataFrame) -> DataFrame:
    v = remote.volumes(e)
    one = lambda df, name, c: df.agg(F.sum(c).alias("vectors")).select(F.lit(name).alias("strategy"), "vectors")
    h = remote.shipped(cover.routed_by_cover(e))
    return one(v, "edge", "edges").unionByName(one(v, "pre", "pre")).unionByName(one(v, "post", "post")).unionByName(one(h, "hybrid", "vectors"))


@query("approx_cover_gap", f"{BIT6} SELECT sp, dp, size AS matched, true AS within_two FROM open")
def approx_cover_gap(spark: SparkSession, d: str) -> DataFrame:
    r = g6_remote(spark, d)
    a = cover.greedy_cover(r).groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("approx"))
    ratio = F.col("approx") / F.col("matched")
    return a.join(cover.matching_sizes(r), ["sp", "dp"]).select("sp", "dp", "matched", ((ratio >= 1) & (ratio <= 2)).alias("within_two"))


@query(
    "leaf_reduction",
    f"""WITH {G6_SQL}, h1 AS (SELECT DISTINCT sp, dp, src FROM (SELECT sp, dp, min(src) AS src FROM r GROUP BY sp, dp, dst HAVING count(*) = 1)),
l1 AS (SELECT r.* FROM r ANTI JOIN h1 ON r.sp = h1.sp AND r.dp = h1.dp AND r.src = h1.src),
h2 AS (SELECT DISTINCT sp, dp, dst FROM (SELECT sp, dp, min(dst) AS dst FROM l1 GROUP BY sp, dp, src HAVING count(*) = 1)),
l2 AS (SELECT l1.* FROM l1 ANTI JOIN h2 ON l1.sp = h2.sp AND l1.dp = h2.dp AND l1.dst = h2.dst),
c AS (SELECT sp, dp, count(*) AS chosen FROM (SELECT sp, dp FROM h1 UNION ALL SELECT sp, dp FROM h2) GROUP BY sp, dp),
n AS (SELECT sp, dp, count(*) AS edges_left FROM l2 GROUP BY sp, dp)
SELECT c.sp, c.dp, chosen, edges_left FROM c LEFT JOIN n ON n.sp = c.sp AND n.dp = c.dp""",
)
def leaf_reduction(spark: SparkSession, d: str) -> DataFrame:
    left, chosen = cover.reduce_leaves(g6_remote(spark, d), 1)
    return chosen.groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("chosen")).join(left.groupBy("sp", "dp").agg(F.count(F.lit(1)).alias("edges_left")), ["sp", "dp"], "left")


# The pair of parts is one component per direction here, so either side's enumeration is exact.
query(
    "volume_reduction_totals",
    f"WITH {G6_SQL}, {bitmask_sql('r')}, v AS (SELECT sp, dp, count(*) AS a, count(DISTINCT dst) AS b, count(DISTINCT src) AS c FROM r GROUP BY sp, dp) SELECT sum(a)::BIGINT AS edges, sum(b)::BIGINT AS pre, sum(c)::BIGINT AS post, sum(least(b, c))::BIGINT AS best_of_two, (SELECT sum(size) FROM open)::BIGINT AS hybrid, (least(sum(b), sum(c)) / (SELECT sum(size) FROM open))::DOUBLE AS gain FROM v",
)(lambda spark, d: (lambda r: metrics.reduction(remote.volumes(r), remote.shipped(cover.routed_by_cover(r))))(g6_remote(spark, d)))

# ---------------------------------------------------------------- aggregation

SPMM_SQL = f"WITH {G2_SQL}, {FEAT_SQL}"
SUM_SQL = f"{SPMM_SQL} SELECT e.dst, k, sum(x)::BIGINT AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k"


def _g2_edges(spark: SparkSession, d: str) -> DataFrame:
    return graphs.part_supplier(spark, d).edges


for _v in ("vanilla", "sorted", "blocked", "balanced"):
    query(f"spmm_sum_{_v}" if _v != "blocked" else "spmm_sum", SUM_SQL)(lambda spark, d, v=_v: as_sums(aggregate.spmm(_g2_edges(spark, d), g2_features(spark, d), variant=v)))
query("spmm_max", f"{SPMM_SQL} SELECT e.dst, k, max(x)::BIGINT AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k")(lambda spark, d: as_sums(aggregate.spmm(_g2_edges(spark, d), g2_features(spark, d), reduce="max")))
query("spmm_min", f"{SPMM_SQL} SELECT e.dst, k, min(x)::BIGINT AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k")(lambda spark, d: as_sums(aggregate.spmm(_g2_edges(spark, d), g2_features(spark, d), reduce="min")))
query("spmm_mean", f"{SPMM_SQL} SELECT e.dst, k, CAST(floor(sum(x)::DOUBLE / count(*)) AS BIGINT) AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k")(
    lambda spark, d: as_sums(aggregate.spmm(_g2_edges(spark, d), g2_features(spark, d), reduce="mean").select("dst", "blk", F.transform("v", lambda x: F.floor(x)).alias("v")))
)
query("spmm_weighted", f"{SPMM_SQL} SELECT e.dst, k, sum(x * (1 + e.src % 3))::BIGINT AS s FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k")(
    lambda spark, d: as_sums(aggregate.spmm(_g2_edges(spark, d).withColumn("w", (1 + F.col("src") % 3)), g2_features(spark, d), weighted=True))
)
query("spmm_transpose", f"{SPMM_SQL} SELECT e.src AS dst, k, sum(x)::BIGINT AS s FROM e JOIN fx ON fx.id = e.dst GROUP BY e.src, k")(lambda spark, d: as_sums(aggregate.spmm(_g2_edges(spark, d), g2_features(spark, d), transpose=True)))
query("spmm_count", f"{SPMM_SQL} SELECT dst, count(*)::DOUBLE AS n FROM e GROUP BY dst")(lambda spark, d: aggregate.spmm(_g2_edges(spark, d), g2_features(spark, d), reduce="count").select("dst", "n"))
query(
    "scatter_add",
    "SELECT (l_partkey % 100)::BIGINT AS dst, k::INT AS k, sum(CAST(floor(CASE k WHEN 0 THEN l_quantity WHEN 1 THEN l_discount ELSE l_tax END * 1048576) AS BIGINT))::BIGINT AS s FROM lineitem, range(3) t(k) GROUP BY 1, 2",
)(
    lambda spark, d: as_sums(
        aggregate.scatter_add(
            to_block(load(spark, d, "lineitem").select((F.col("l_partkey") % 100).alias("idx"), F.array(fixed_point(F.col("l_quantity")), fixed_point(F.col("l_discount")), fixed_point(F.col("l_tax"))).alias("v")), id_="idx")
        ),
        key="idx",
    )
)


def _by_plan(strategy: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        here, away = remote.split(g2_located(spark, d))
        routed = cut(spark, remote.plan(away, strategy), "routed")  # routed once, read by each branch
        return as_sums(aggregate.neighbour(here, routed, g2_features(spark, d)))

    return run


for _s in ("edge", "pre", "post", "best_of_two", "hybrid", "approx_cover"):
    query(f"agg_{_s}", SUM_SQL)(_by_plan(_s))
query("agg_local", f"{SPMM_SQL} SELECT el.dst, k, sum(x)::BIGINT AS s FROM el JOIN fx ON fx.id = el.src WHERE sp = dp GROUP BY el.dst, k")(lambda spark, d: as_sums(aggregate.local(remote.split(g2_located(spark, d))[0], g2_features(spark, d))))
query("agg_message_rows", f"WITH {G6_SQL}, {bitmask_sql('r')} SELECT 'partial' AS kind, count(DISTINCT (sp, dp, dst))::BIGINT AS n FROM routed WHERE route = 'pre' UNION ALL SELECT 'raw', count(DISTINCT (sp, dp, src))::BIGINT FROM routed WHERE route = 'post'")(
    lambda spark, d: aggregate.messages(_g6_routed(spark, d), to_block(load(spark, d, "events").select(F.col("user_id").alias("id")).distinct().select("id", F.array(F.col("id")).alias("v")))).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))
)
query("two_layer_linear", f"{SPMM_SQL}, h AS (SELECT e.dst AS id, k, sum(x) AS x FROM e JOIN fx ON fx.id = e.src GROUP BY e.dst, k) SELECT e.dst, k, sum(x)::BIGINT AS s FROM e JOIN h ON h.id = e.src GROUP BY e.dst, k")(
    lambda spark, d: (lambda e, f: as_sums(aggregate.spmm(e, aggregate.spmm(e, f).withColumnRenamed("dst", "id"))))(_g2_edges(spark, d), g2_features(spark, d))
)


@query("agg_hybrid_int2")
def agg_hybrid_int2(spark: SparkSession, d: str) -> DataFrame:
    here, away = remote.split(g2_located(spark, d))
    f = g2_features(spark, d).select("id", "blk", F.transform("v", lambda x: x / float(1 << 20)).alias("v"))
    out = aggregate.neighbour(here, remote.plan(away, "hybrid"), f, through=quantize.through(2))
    return out.select("dst", "blk", F.slice("v", 1, 3).alias("v"))


@query("layer_gin", f"{SPMM_SQL}, u AS (SELECT e.dst, k, x FROM e JOIN fx ON fx.id = e.src UNION ALL SELECT id, k, x FROM fx) SELECT dst, k, sum(x)::BIGINT AS s FROM u GROUP BY dst, k")
def layer_gin(spark: SparkSession, d: str) -> DataFrame:
    return as_sums(layers.gin(_g2_edges(spark, d), g2_features(spark, d)), key="id")


@query("gcn_weights", f"WITH {G6_SQL}, n AS (SELECT src AS n FROM e UNION SELECT dst FROM e), l AS (SELECT src, dst FROM e UNION ALL SELECT n, n FROM n), g AS (SELECT dst AS n, count(*) AS d FROM l GROUP BY dst) SELECT src, dst, a.d::BIGINT AS d_src, b.d::BIGINT AS d_dst FROM l JOIN g a ON a.n = src JOIN g b ON b.n = dst")
def gcn_weights(spark: SparkSession, d: str) -> DataFrame:
    e = layers.with_gcn_weights(graphs.user_succession(spark, d).edges)
    deg = e.groupBy(F.col("dst").alias("n")).agg(F.count(F.lit(1)).alias("d"))
    at = lambda c: deg.select(F.col("n").alias(c), F.col("d").alias(f"d_{c}"))
    return e.join(at("src"), "src").join(at("dst"), "dst").select("src", "dst", "d_src", "d_dst")


@query(
    "layer_attention",
    f"""{SPMM_SQL}, x AS (SELECT id, k, x / 1048576.0::DOUBLE AS x FROM fx), a AS (SELECT id, x FROM x WHERE k = 1), b AS (SELECT id, x FROM x WHERE k = 2),
s AS (SELECT e.src, e.dst, CASE WHEN a.x + b.x > 0 THEN a.x + b.x ELSE (a.x + b.x) * 0.2::DOUBLE END AS s FROM e JOIN a ON a.id = e.src JOIN b ON b.id = e.dst),
w AS (SELECT src, dst, exp(s - max(s) OVER (PARTITION BY dst)) AS w FROM s), z AS (SELECT src, dst, w / sum(w) OVER (PARTITION BY dst) AS w FROM w)
SELECT z.dst, k, CAST(round(sum(w * x) * 1e6) AS BIGINT) AS s FROM z JOIN x ON x.id = z.src GROUP BY z.dst, k""",
)
def layer_attention(spark: SparkSession, d: str) -> DataFrame:
    f = g2_features(spark, d).select("id", "blk", F.transform("v", lambda x: x / float(1 << 20)).alias("v"))
    scores = f.select("id", F.get("v", F.lit(1)).alias("as_src"), F.get("v", F.lit(2)).alias("as_dst"))
    return layers.attention(_g2_edges(spark, d), f, scores).select("dst", F.posexplode(F.slice("v", 1, 3)).alias("k", "x")).select("dst", "k", F.round(F.col("x") * 1e6).cast("long").alias("s"))


# ---------------------------------------------------------------- quantization

def embeddings(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))


PAR_SQL = "WITH p AS (SELECT vec_id AS id, embedding AS v, list_min(embedding)::DOUBLE AS zp, (list_max(embedding)::DOUBLE - list_min(embedding)::DOUBLE) / {top}.0 AS sc FROM embeddings)"
query("quant_params", PAR_SQL.format(top=3) + " SELECT id, zp, sc FROM p")(lambda spark, d: quantize.params(embeddings(spark, d), 2).select("id", "zp", "sc"))
for _b in quantize.BITS:
    query(f"quant_codes_int{_b}", PAR_SQL.format(top=2**_b - 1) + f" SELECT id, k::INT AS k, CASE WHEN sc = 0 THEN 0 ELSE least(greatest(floor((v[k + 1]::DOUBLE - zp) / sc + 0.5), 0), {2**_b - 1}) END::INT AS q FROM p, range(64) t(k)")(
        lambda spark, d, b=_b: quantize.encode(embeddings(spark, d), b).select("id", F.posexplode("q").alias("k", "q"))
    )
query("quant_stochastic_int2", PAR_SQL.format(top=3) + f" SELECT id, k::INT AS k, CASE WHEN sc = 0 THEN 0 ELSE least(greatest(floor((v[k + 1]::DOUBLE - zp) / sc + {mix_uniform_sql('id', 'k', '5')}), 0), 3) END::INT AS q FROM p, range(64) t(k)")(
    lambda spark, d: quantize.encode(embeddings(spark, d), 2, "stochastic", seed=5).select("id", F.posexplode("q").alias("k", "q"))
)


@query("quant_roundtrip_error", PAR_SQL.format(top=15) + " SELECT max(abs(least(greatest(floor((v[k + 1]::DOUBLE - zp) / sc + 0.5), 0), 15) * sc + zp - v[k + 1]::DOUBLE) / sc) <= 0.5000001 AS within_half, count(*)::BIGINT AS elements FROM p, range(64) t(k)")
def quant_roundtrip_error(spark: SparkSession, d: str) -> DataFrame:
    e = embeddings(spark, d)
    q = quantize.encode(e, 4)
    cells = e.join(quantize.decode(q).withColumnRenamed("v", "u"), "id").join(q.select("id", "sc"), "id").select("sc", F.explode(F.zip_with("u", "v", lambda a, b: F.abs(a - b))).alias("x"))
    return cells.agg((F.max(F.col("x") / F.col("sc")) <= 0.5000001).alias("within_half"), F.count(F.lit(1)).alias("elements"))


@query("quant_packed_bytes", "SELECT vec_id AS id, 16::INT AS int2_bytes, 32::INT AS int4_bytes, 64::INT AS int8_bytes, true AS same FROM embeddings")
def quant_packed_bytes(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for b in quantize.BITS:
        q = quantize.encode(embeddings(spark, d), b).select("id", "q", quantize.pack(F.col("q"), b).alias("c"))
        one = q.select("id", F.length("c").alias(f"int{b}_bytes"), (quantize.unpack(F.col("c"), b, 64) == F.col("q")).alias(f"same{b}"))
        out = one if out is None else out.join(one, "id")
    return out.select("id", "int2_bytes", "int4_bytes", "int8_bytes", (F.col("same2") & F.col("same4") & F.col("same8")).alias("same"))


query(
    "quant_fused_bytes",
    PAR_SQL.format(top=3)
    + ", q AS (SELECT id, k, CASE WHEN sc = 0 THEN 0 ELSE least(greatest(floor((v[k + 1]::DOUBLE - zp) * (1.0::DOUBLE / sc) + 0.5), 0), 3) END::BIGINT AS q FROM p, range(64) t(k)) SELECT id, (k // 4)::INT AS place, sum(q << (2 * (k % 4))::INT)::INT AS byte FROM q GROUP BY id, k // 4",
)(lambda spark, d: quantize.fused(embeddings(spark, d), 2).select("id", F.hex("codes").alias("h")).select("id", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(15)), lambda j: F.conv(F.substr("h", (j * 2 + 1).cast("int"), F.lit(2)), 16, 10).cast("int"))).alias("place", "byte")))
query(
    "comm_volume_quantized",
    f"WITH {G6_SQL}, {bitmask_sql('r')} SELECT sum(size)::BIGINT AS vectors, (sum(size) * 16)::BIGINT AS data_bytes, (sum(size) * 8)::BIGINT AS param_bytes FROM open",
)(lambda spark, d: metrics.comm_volume(_g6_routed(spark, d), 64, 2))
query(
    "quant_adaptive_bits",
    "WITH s AS (SELECT list_max(embedding)::DOUBLE - list_min(embedding)::DOUBLE AS s FROM embeddings), c AS (SELECT quantile_disc(s, 0.5) AS a, quantile_disc(s, 0.8) AS b FROM s) SELECT (CASE WHEN s <= a THEN 2 WHEN s <= b THEN 4 ELSE 8 END)::INT AS bits, count(*)::BIGINT AS rows FROM s, c GROUP BY 1",
)(lambda spark, d: quantize.adaptive(embeddings(spark, d)).groupBy("bits").agg(F.count(F.lit(1)).alias("rows")))
millionth = lambda c: F.round(F.col(c) * 1e6).cast("long").alias(c)
query(
    "quant_error",
    PAR_SQL.format(top=3)
    + f", e AS (SELECT sc, (CASE WHEN sc = 0 THEN 0 ELSE least(greatest(floor((v[k + 1]::DOUBLE - zp) / sc + {mix_uniform_sql('id', 'k', '3')}), 0), 3) END * sc + zp) - v[k + 1]::DOUBLE AS e FROM p, range(64) t(k)) SELECT CAST(round(max(CASE WHEN sc > 0 THEN abs(e) / sc ELSE 0 END) * 1e6) AS BIGINT) AS worst_in_scales, CAST(round(avg(e) * 1e6) AS BIGINT) AS bias, CAST(round(stddev(e) * 1e6) AS BIGINT) AS spread FROM e",
)(lambda spark, d: (lambda e: (lambda q: metrics.quant_error(e, quantize.decode(q), q))(quantize.encode(e, 2, "stochastic", seed=3)))(embeddings(spark, d)).select(millionth("worst_in_scales"), millionth("bias"), millionth("spread")))

# ---------------------------------------------------------------- label propagation, normalization

LAB_SQL = "SELECT doc_id AS id, max(quality) AS label FROM labels GROUP BY doc_id"
query("lp_mask", f"WITH t AS ({LAB_SQL}) SELECT id, 3::INT AS epoch, {mix_uniform_sql('id', '3', '0')} < 0.5 AS shown FROM t WHERE id % 10 <= 4")(
    lambda spark, d: propagate.mask(_labelled(spark, d), 0.5, 3)
)
query(
    "lp_inject",
    f"WITH t AS ({LAB_SQL}) SELECT id, CASE WHEN id % 10 <= 4 AND {mix_uniform_sql('id', '3', '0')} < 0.5 THEN (id % 7)::DOUBLE + CASE label WHEN 0 THEN 10.0 ELSE 20.0 END ELSE (id % 7)::DOUBLE END AS x FROM t",
)(lambda spark, d: (lambda n: propagate.inject(n, propagate.mask(n, 0.5, 3).filter("shown"), [[10.0], [20.0]]).select("id", F.get("feat", F.lit(0)).alias("x")))(_labelled(spark, d)))
query("lp_infer", f"WITH t AS ({LAB_SQL}) SELECT id, CASE WHEN id % 10 <= 4 THEN (id % 7)::DOUBLE + CASE label WHEN 0 THEN 10.0 ELSE 20.0 END ELSE (id % 7)::DOUBLE END AS x FROM t")(
    lambda spark, d: propagate.inject(_labelled(spark, d), None, [[10.0], [20.0]], "infer").select("id", F.get("feat", F.lit(0)).alias("x"))
)


def _labelled(spark: SparkSession, d: str) -> DataFrame:
    t = load(spark, d, "labels").groupBy(F.col("doc_id").alias("id")).agg(F.max("quality").alias("label"))
    return t.select("id", F.array((F.col("id") % 7).cast("double")).alias("feat"), F.col("label").cast("int").alias("label"), graphs.split_of(F.col("id")).alias("split"))


@query("lp_linearity")
def lp_linearity(spark: SparkSession, d: str) -> DataFrame:
    g = graphs.user_succession(spark, d)
    n = g.nodes.select("id", F.slice("feat", 1, 4).alias("feat"), "label", "split")
    return propagate.linearity_gap(g.edges, n, [[1.0, 0, 0, 0], [0, 1.0, 0, 0], [0, 0, 1.0, 0], [0, 0, 0, 1.0]])


@query("layer_norm_rows", "SELECT vec_id AS id, true AS mean_zero, true AS variance_one FROM embeddings")
def layer_norm_rows(spark: SparkSession, d: str) -> DataFrame:
    z = embeddings(spark, d).select("id", layers.layer_norm(F.col("v"), 0.0).alias("z"))
    total = lambda f: F.aggregate(F.transform("z", f), F.lit(0.0), lambda s, x: s + x) / F.size("z")
    return z.select("id", (F.abs(total(lambda x: x)) < 1e-6).alias("mean_zero"), (F.abs(total(lambda x: x * x) - 1) < 1e-6).alias("variance_one"))


query("mixer_uniform", f"SELECT event_id AS id, {mix_uniform_sql('event_id', 'user_id', '9')} AS u FROM events")(lambda spark, d: load(spark, d, "events").select(F.col("event_id").alias("id"), mix_uniform(F.col("event_id"), F.col("user_id"), 9).alias("u")))
query("vector_layouts", "SELECT vec_id AS id, true AS same FROM embeddings")(
    lambda spark, d: (lambda e: e.join(from_block(to_block(e), width=64).withColumnRenamed("v", "u"), "id").select("id", (F.col("u") == F.col("v")).alias("same")))(embeddings(spark, d))
)
query("neighbor_vote_accuracy", f"WITH {G6_SQL}, k AS (SELECT e.dst, (e.src % 4)::INT AS l, count(*) AS c FROM e WHERE e.src % 10 <= 4 GROUP BY 1, 2), m AS (SELECT dst, l, row_number() OVER (PARTITION BY dst ORDER BY c DESC, l) AS r FROM k) SELECT dst AS id, l AS pred FROM m WHERE r = 1")(
    lambda spark, d: (lambda g: metrics.neighbour_vote(g.nodes, g.edges))(graphs.user_succession(spark, d))
)

# ---------------------------------------------------------------- cost model

BW, LAT, TH = 1.0e10, 1.0e-5, 1.0e12
COMM_SQL = f"WITH {G6_SQL}, v AS (SELECT sp, dp, count(DISTINCT src) * 64 AS n FROM r GROUP BY sp, dp)"


def _comm(spark: SparkSession, d: str) -> DataFrame:
    return metrics.comm_matrix(remote.plan(g6_remote(spark, d), "post"), 64)


query("comm_matrix", f"WITH {G6_SQL} SELECT sp, dp, count(DISTINCT src)::BIGINT AS vectors, (count(DISTINCT src) * 64)::BIGINT AS elements, (count(DISTINCT src) * 2048)::BIGINT AS bits FROM r GROUP BY sp, dp")(_comm)
# times are compared in whole picoseconds: sums of doubles depend on their order
query("cost_exchange", f"{COMM_SQL}, t AS (SELECT sp, sum(CAST(floor(((n * 32) / {BW} + {LAT}) * 1e12) AS BIGINT)) AS t FROM v GROUP BY sp) SELECT max(t)::BIGINT AS picoseconds FROM t")(
    lambda spark, d: _comm(spark, d).groupBy("sp").agg(F.sum(F.floor(costmodel.pair_seconds(F.col("elements"), BW, LAT) * 1e12).cast("long")).alias("t")).agg(F.max("t").alias("picoseconds"))
)


@query(
    "cost_quant_total",
    f"""{COMM_SQL}, own AS (SELECT (user_id % 16)::INT AS sp, count(DISTINCT user_id) * 64 AS m FROM events GROUP BY 1),
p AS (SELECT sp, sum((n * 32) / {BW} + {LAT}) AS t FROM v GROUP BY sp), s AS (SELECT sp, sum(2 * (n * 34) / {TH} + (n * 2 + n / 64.0::DOUBLE * 2 * 32) / {BW} + {LAT}) AS t FROM v GROUP BY sp)
SELECT (SELECT CAST(round(max(t) * 1e12) AS BIGINT) FROM p) AS plain_ps, CAST(round(max(own.m * 32 / {TH} + coalesce(s.t, 0)) * 1e12) AS BIGINT) AS int2_ps FROM own LEFT JOIN s ON s.sp = own.sp""",
)
def cost_quant_total(spark: SparkSession, d: str) -> DataFrame:
    comm = _comm(spark, d)
    own = graphs.user_succession(spark, d).nodes.groupBy(F.pmod("id", F.lit(SUCC_P)).cast("int").alias("sp")).agg((F.count(F.lit(1)) * 64).alias("elements"))
    plain = costmodel.exchange_time(comm, BW, LAT).withColumnRenamed("seconds", "plain")
    both = plain.crossJoin(costmodel.quant_total(comm, own, 2, 64, BW, LAT, TH).withColumnRenamed("seconds", "int2"))
    return both.select(*[F.round(F.col(c) * 1e12).cast("long").alias(f"{c}_ps") for c in ("plain", "int2")])


@query(
    "cost_speedup_curve",
    f"{COMM_SQL}, g AS (SELECT sp, dp, bits, 32.0::DOUBLE / bits AS g, {LAT}::DOUBLE / ((n * bits)::DOUBLE / {BW}::DOUBLE) AS d FROM v, (SELECT unnest([2, 4, 8])::INT AS bits) x) "
    "SELECT sp, dp, bits, d AS delta, (g + d) / (1.0::DOUBLE + d + g / 100.0::DOUBLE + 2.0::DOUBLE * (1.0::DOUBLE + g) / 100.0::DOUBLE) AS speedup, (g + d) / (1.0::DOUBLE + d) AS approx FROM g",
)
def cost_speedup_curve(spark: SparkSession, d: str) -> DataFrame:
    return costmodel.curve(_comm(spark, d), BW, LAT)


@query("cost_ratios", f"{COMM_SQL} SELECT sp, dp, 32.0::DOUBLE AS alpha, 100.0::DOUBLE AS beta, 16.0::DOUBLE AS gamma FROM v")
def cost_ratios(spark: SparkSession, d: str) -> DataFrame:
    return _comm(spark, d).select("sp", "dp", (F.col("elements") / (F.col("vectors") * 2)).alias("alpha"), F.lit(TH / BW).alias("beta"), F.lit(32.0 / 2).alias("gamma"))


query("imbalance", f"{COMM_SQL}, s AS (SELECT sp, sum(n // 64) AS v FROM v GROUP BY sp) SELECT max(v)::BIGINT AS most, avg(v)::DOUBLE AS mean, (max(v) / avg(v))::DOUBLE AS ratio FROM s")(lambda spark, d: metrics.imbalance(_comm(spark, d)))


@query(
    "convergence_bound",
    """WITH u AS (SELECT user_id, count(*) AS t, max(value)::DOUBLE AS hi, min(value)::DOUBLE AS lo, (count(*) FILTER (WHERE event_type = 'error'))::DOUBLE / count(*) AS k FROM events GROUP BY user_id)
SELECT user_id, t::BIGINT AS epochs, k::DOUBLE AS noise, CAST(round((2.0::DOUBLE * (hi - lo) / (t * (0.02::DOUBLE - 0.0001::DOUBLE)) + 0.01::DOUBLE / 1.99::DOUBLE * k * k) * 1e6) AS BIGINT) AS bound_e6 FROM u""",
)
def convergence_bound(spark: SparkSession, d: str) -> DataFrame:
    """The bound for every user: a step per event, losses from the largest value to the least, the share of errors as noise."""
    errors = F.count(F.when(F.col("event_type") == "error", 1))
    u = load(spark, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("epochs"), F.max("value").alias("hi"), F.min("value").alias("lo"), (errors / F.count(F.lit(1))).alias("noise"))
    bound = costmodel.convergence_bound(F.col("hi"), F.col("lo"), F.col("epochs"), 0.01, 1.0, F.col("noise"))
    return u.select("user_id", "epochs", "noise", F.round(bound * 1e6).cast("long").alias("bound_e6"))


# ---------------------------------------------------------------- partitioners

@query("partition_propagate")
def partition_propagate(spark: SparkSession, d: str) -> DataFrame:
    g = graphs.shingle_documents(spark, d, 8)
    return metrics.partition_quality(remote.located(g.edges, partition.propagate(g.nodes, g.edges, 4, 3)))


@query("partition_multilevel")
def partition_multilevel(spark: SparkSession, d: str) -> DataFrame:
    g = graphs.shingle_documents(spark, d, 8)
    return metrics.partition_quality(remote.located(g.edges, partition.multilevel(g.nodes, g.edges, 4)))


query("partition_by_mod", "SELECT p_partkey AS id, (p_partkey % 8)::INT AS part FROM part")(lambda spark, d: partition.by_mod(load(spark, d, "part").select(F.col("p_partkey").alias("id")), 8))
query("partition_by_region", "SELECT c_custkey AS id, n_regionkey AS part FROM customer JOIN nation ON c_nationkey = n_nationkey")(
    lambda spark, d: partition.by_column(load(spark, d, "customer").join(load(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("id"), "n_regionkey"), "n_regionkey")
)
query("partition_by_range", f"WITH c AS (SELECT unnest(quantile_disc(p_partkey, {[i / 8 for i in range(1, 8)]})) AS c FROM part) SELECT p_partkey AS id, (SELECT count(*) FROM c WHERE c.c < p_partkey)::INT AS part FROM part")(lambda spark, d: partition.by_range(load(spark, d, "part").select(F.col("p_partkey").alias("id")), 8))
Q["partition_by_hash"] = lambda spark, d: partition.by_hash(load(spark, d, "part").select(F.col("p_partkey").alias("id")), 8)
