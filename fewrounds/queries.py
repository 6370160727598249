"""Queries over the given tables for every method, baseline, measure and relational family, with their SQL twins."""

from __future__ import annotations

import math
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import twins
from .functions.coins import coin, cosine_distance
from .functions.params import params_for
from .operators import analysis, baselines, connectivity, graphs, msf, nested, reductions, sampling, sketches, sparsify
from .operators import relational as rel
from .operators.components import ComponentResult, as_links, canonical_labels, complete_partition, publish_forest
from .plans import ledger
from .plans.spool import cut
from .sources import derive
from .sources.tables import TABLES, read_table, register_views
from .streaming import graph_streams as gs

QUERIES: dict = {}
SQL: dict[str, str] = {}
T = {k: k * graphs.TAG for k in range(1, 12)}


def add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


# graphs in SQL

_H = "('0x' || substr(md5({}), 1, 9))::BIGINT"
EDGES = {
    "part_supplier": f"SELECT {T[1]} + l_partkey AS src, {T[2]} + l_suppkey AS dst, min(l_extendedprice) AS weight FROM lineitem GROUP BY 1, 2",
    "order_part": f"SELECT DISTINCT {T[1]} + l_partkey AS src, {T[3]} + l_orderkey AS dst FROM lineitem",
    "customer_order": f"SELECT {T[1]} + o_custkey AS src, {T[3]} + o_orderkey AS dst, min(o_totalprice) AS weight FROM orders GROUP BY 1, 2",
    "order_chain": "SELECT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS b FROM orders) WHERE b IS NOT NULL",
    "order_path": "SELECT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT o_orderkey AS a, lead(o_orderkey) OVER (ORDER BY o_orderdate, o_orderkey) AS b FROM orders) WHERE b IS NOT NULL",
    "conv_chain": "SELECT a AS src, b AS dst FROM (SELECT conv_id * 10000 + turn AS a, lead(conv_id * 10000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations) WHERE b IS NOT NULL",
    "doc_line": f"SELECT DISTINCT {T[4]} + doc_id AS src, {T[5]} + {_H.format('line')} AS dst FROM (SELECT doc_id, line, count(*) OVER (PARTITION BY line) AS n FROM (SELECT DISTINCT doc_id, trim(l) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents)) WHERE length(line) >= 40) WHERE n BETWEEN 2 AND 20",
    "doc_line_all": f"SELECT DISTINCT {T[4]} + doc_id AS src, {T[5]} + {_H.format('line')} AS dst FROM (SELECT doc_id, line, count(*) OVER (PARTITION BY line) AS n FROM (SELECT DISTINCT doc_id, trim(l) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents)) WHERE length(line) >= 40) WHERE n >= 2",
    "page_host": f"SELECT DISTINCT {T[6]} + page_id AS src, {T[7]} + {_H.format('h')} AS dst FROM (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS h FROM pages)",
    "page_link": f"SELECT DISTINCT {T[6]} + page_id AS src, {T[8]} + {_H.format('t')} AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages)",
    "geo_tree": f"SELECT {T[2]} + s_suppkey AS src, {T[9]} + s_nationkey AS dst FROM supplier UNION SELECT {T[1]} + c_custkey, {T[9]} + c_nationkey FROM customer UNION SELECT {T[9]} + n_nationkey, {T[10]} + n_regionkey FROM nation",
    "user_hour": "WITH h AS (SELECT DISTINCT user_id, date_trunc('hour', ts) AS h FROM events) SELECT a.user_id AS src, b.user_id AS dst, -count(*)::DOUBLE AS weight FROM h a JOIN h b ON a.h = b.h AND a.user_id < b.user_id GROUP BY 1, 2",
    "supplier_line": "SELECT a.s_suppkey AS src, b.s_suppkey AS dst, abs(a.s_acctbal - b.s_acctbal) AS weight FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey",
}
VERTICES = {
    "customer_order": f"SELECT {T[1]} + c_custkey AS vid FROM customer UNION SELECT {T[3]} + o_orderkey FROM orders",
    "order_chain": "SELECT o_orderkey AS vid FROM orders",
    "order_path": "SELECT o_orderkey AS vid FROM orders",
    "conv_chain": "SELECT conv_id * 10000 + turn AS vid FROM conversations",
    "doc_line": f"SELECT {T[4]} + doc_id AS vid FROM documents",
    "doc_line_all": f"SELECT {T[4]} + doc_id AS vid FROM documents",
    "user_hour": "SELECT DISTINCT user_id AS vid FROM events",
    "supplier_line": "SELECT s_suppkey AS vid FROM supplier",
}


def with_cc(graph: str, tail: str, more: str = "") -> str:
    """SQL with e (src, dst), v (vid) and c (vid, comp: least vid of the component)."""
    own = f"{VERTICES[graph]} UNION " if graph in VERTICES else ""
    return f"""WITH RECURSIVE e AS ({EDGES[graph]}), v AS (SELECT DISTINCT vid FROM ({own}SELECT src AS vid FROM e UNION SELECT dst FROM e)),
s AS (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e),
c(vid, comp) USING KEY (vid) AS (SELECT vid, vid FROM v UNION (SELECT s.b AS vid, min(c.comp) AS comp FROM c JOIN s ON c.vid = s.a JOIN recurring.c k ON k.vid = s.b WHERE c.comp < k.comp GROUP BY s.b)){more}
{tail}"""


def _cc(graph: str):
    build = derive.user_hour_links if graph == "user_hour" else derive.GRAPHS[graph]
    return lambda spark, d: connectivity.connected_components(build(spark, d)).labels


for _g in ("part_supplier", "order_part", "customer_order", "order_chain", "conv_chain", "doc_line", "doc_line_all", "page_host", "page_link", "geo_tree", "user_hour"):
    add(f"cc_{_g}", _cc(_g), with_cc(_g, "SELECT vid, comp FROM c"))
add("cc_order_path", _cc("order_path"), "SELECT o_orderkey AS vid, min(o_orderkey) OVER () AS comp FROM orders")
add(
    "cc_caterpillar",
    _cc("caterpillar"),
    f"WITH o AS (SELECT o_orderkey AS k, min(o_orderkey) OVER (PARTITION BY strftime(o_orderdate, '%Y-%m')) AS m FROM orders), l AS (SELECT l_orderkey AS k, row_number() OVER (PARTITION BY l_orderkey) AS i FROM lineitem) SELECT {T[3]} + k AS vid, {T[3]} + m AS comp FROM o UNION ALL SELECT {T[11]} + l.k * 1000 + i, {T[3]} + m FROM l JOIN o ON l.k = o.k",
)


def _forest(graph: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = derive.GRAPHS[graph](spark, d)
        return analysis.forest_checks(g, connectivity.connected_components(g))

    return run


for _g in ("order_part", "customer_order", "order_chain", "doc_line", "doc_line_all", "page_host"):
    add(f"forest_checks_{_g}", _forest(_g), with_cc(_g, "SELECT count(*) AS n, count(DISTINCT comp) AS components, count(*) - count(DISTINCT comp) AS forest_edges, true AS size_ok, true AS inside_ok, true AS spans_ok FROM c"))


def publish(spark: SparkSession, d: str) -> DataFrame:
    g = derive.conv_chain(spark, d)
    p = publish_forest(g.vertices, connectivity.connected_components(g))
    return p.groupBy("root").agg(F.count(F.lit(1)).alias("size"), F.max("depth").alias("depth"))


add("publish_forest_conv_chain", publish, "SELECT min(conv_id * 10000 + turn) AS root, count(*) AS size, count(*) - 1 AS depth FROM conversations GROUP BY conv_id")


# sparsification


def hooks1(spark: SparkSession, d: str, graph: str = "order_part") -> DataFrame:
    g = derive.GRAPHS[graph](spark, d)
    return sparsify.hook_to_top_neighbour(g, graphs.degrees(g)).select("v", "u")


add("sparsify_hooks1", hooks1, f"WITH e AS ({EDGES['order_part']}), s AS (SELECT src AS v, dst AS u FROM e UNION ALL SELECT dst, src FROM e), g AS (SELECT v, count(*) AS d FROM s GROUP BY v) SELECT s.v, s.u FROM s JOIN g ON s.u = g.v QUALIFY row_number() OVER (PARTITION BY s.v ORDER BY d DESC, s.u DESC) = 1")


def stage1_labels(spark: SparkSession, d: str) -> DataFrame:
    g = derive.order_part(spark, d)
    return sparsify.stage_one(g, cut(graphs.degrees(g)))[1]


_STAGE1 = f"""WITH RECURSIVE e AS ({EDGES["order_part"]}), s AS (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e), g AS (SELECT a AS v, count(*) AS d FROM s GROUP BY a),
h AS (SELECT s.a, s.b FROM s JOIN g ON s.b = g.v QUALIFY row_number() OVER (PARTITION BY s.a ORDER BY d DESC, s.b DESC) = 1), l AS (SELECT a, b FROM h UNION SELECT b, a FROM h),
c(vid, comp) USING KEY (vid) AS (SELECT v, v FROM g UNION (SELECT l.b AS vid, min(c.comp) AS comp FROM c JOIN l ON c.vid = l.a JOIN recurring.c k ON k.vid = l.b WHERE c.comp < k.comp GROUP BY l.b)),
m AS (SELECT comp, max(d) AS cdeg FROM c JOIN g ON c.vid = g.v GROUP BY comp)"""
add("sparsify_stage1_labels", stage1_labels, f"{_STAGE1} SELECT vid, c.comp, cdeg FROM c JOIN m ON c.comp = m.comp")


def hooks2(spark: SparkSession, d: str) -> DataFrame:
    g = derive.order_part(spark, d)
    return sparsify.hook_to_top_component(g, sparsify.stage_one(g, cut(graphs.degrees(g)))[1])


add("sparsify_hooks2", hooks2, f"{_STAGE1} SELECT s.a AS v, s.b AS u FROM s JOIN c x ON s.a = x.vid JOIN c y ON s.b = y.vid JOIN m ON y.comp = m.comp WHERE x.comp <> y.comp QUALIFY row_number() OVER (PARTITION BY s.a ORDER BY cdeg DESC, y.comp DESC, s.b DESC) = 1")


SPLIT = ("awake_components", "least_size", "deg_b", "edges_a", "edges_b")


def _vertices(graph: str) -> str:
    return VERTICES.get(graph, "SELECT NULL::BIGINT AS vid WHERE false")


def sparsify_invariants(spark: SparkSession, d: str) -> DataFrame:
    """The split's counts at two degrees, and whether they keep within n / s, s + 1 and s."""
    out = None
    for name in ("order_part", "customer_order", "doc_line", "page_host"):
        g = derive.GRAPHS[name](spark, d)
        g = g.settle()
        for s in (2, 8):
            m = analysis.split_measures(g, sparsify.sparsify_by_degree(g, s), s).select(F.lit(name).alias("graph"), F.lit(s).alias("s"), *SPLIT, "count_ok", "size_ok", "degree_ok")
            out = m if out is None else out.unionByName(m)
    return out


def _invariants(graph: str, s: int) -> str:
    counts = f"(WITH RECURSIVE {twins.degree_split(EDGES[graph], _vertices(graph), str(s))} SELECT '{graph}' AS graph, {s} AS s, {twins.SPLIT_COUNTS}, n FROM p)"
    return f"SELECT * EXCLUDE (n), awake_components * s <= n AS count_ok, awake_components = 0 OR least_size >= s + 1 AS size_ok, deg_b < s AS degree_ok FROM {counts}"


add("sparsify_invariants", sparsify_invariants, " UNION ALL ".join(_invariants(g, s) for g in ("order_part", "customer_order", "doc_line", "page_host") for s in (2, 8)))


def split_counts(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in ("customer_order", "doc_line", "page_host", "order_chain"):
        g = derive.GRAPHS[name](spark, d)
        s = params_for(g.n).s
        one = analysis.split_measures(g, sparsify.sparsify_by_degree(g, s, second_stage=False), s).select("awake_components")
        m = analysis.split_measures(g, sparsify.sparsify_by_degree(g, s), s).select(F.lit(name).alias("graph"), F.lit(s).alias("s"), *SPLIT).join(one.withColumnRenamed("awake_components", "awake_stage1_only"))
        out = m if out is None else out.unionByName(m)
    return out


add(
    "sparsify_split_counts",
    split_counts,
    " UNION ALL ".join(
        f"(WITH RECURSIVE {twins.degree_split(EDGES[g], _vertices(g))} SELECT '{g}' AS graph, s::INTEGER AS s, {twins.SPLIT_COUNTS}, (SELECT count(*) FROM m1 WHERE cdeg >= s) AS awake_stage1_only FROM p)" for g in ("customer_order", "doc_line", "page_host", "order_chain")
    ),
)


# sampling

_L = 3.0


def sample_sizes(spark: SparkSession, d: str) -> DataFrame:
    return sampling.sample_edges(derive.order_chain(spark, d).edges, 16, 0.25, 1, portable=True).groupBy("sample").agg(F.count(F.lit(1)).alias("edges"))


_COIN = "('0x' || substr(md5(concat_ws('|', '{seed}', '{purpose}', {keys})), 1, 8))::BIGINT / 4294967296.0"
add("sample_sizes_md5", sample_sizes, f"SELECT sample, count(*) AS edges FROM (SELECT e.*, unnest(range(1, 17))::INTEGER AS sample FROM ({EDGES['order_chain']}) e) WHERE {_COIN.format(seed=1, purpose='sample', keys='sample::VARCHAR, src::VARCHAR, dst::VARCHAR')} < 0.25 GROUP BY sample")
add("leaders_md5", lambda spark, d: sampling.choose_leaders(derive.order_chain(spark, d).vertices, 0.25, 1, portable=True), f"SELECT o_orderkey AS vid FROM orders WHERE {_COIN.format(seed=1, purpose='leader', keys='o_orderkey::VARCHAR')} < 0.25")


def _contracted(spark: SparkSession, d: str, graph: str, **options):
    """A contraction with the method's own parameters and portable coins."""
    g = derive.GRAPHS[graph](spark, d)
    g = g.settle()
    p = params_for(g.n, seed=options.pop("seed", 1), **{k: v for k, v in options.items() if k not in ("labels_only", "count_messages")})
    only_counted = options.get("count_messages", False)
    return g, p, sampling.contract_by_samples(g, p, options.get("labels_only", False), not only_counted, portable=True, count_messages=only_counted)


def _twin(graph: str, select: str, seed: int = 1, more: str = "", **options) -> str:
    return f"(WITH RECURSIVE {twins.contraction(EDGES[graph], _vertices(graph), seed, **options)}{more} {select})"


def contract_verdict(spark: SparkSession, d: str) -> DataFrame:
    """After one contraction of sparse graphs: samples and messages, components, growable ones and whether these are at
    most 1.5 n / L (which one sample alone misses), forest edges, and those outside the graph or the components."""
    out = None
    for name in ("order_chain", "order_path", "conv_chain"):
        g, p, (labels, forest, messages) = _contracted(spark, d, name, count_messages=True)
        forest = cut(forest)
        spanned, _ = complete_partition(as_links(forest))
        amiss = forest.join(g.edges, ["src", "dst"], "left_anti").count() + canonical_labels(g.vertices, spanned).exceptAll(canonical_labels(g.vertices, labels)).count()
        grow = graphs.growable(labels, g.edges).count()
        row = [(name, g.n, p.num_samples, messages.agg(F.sum("held")).first()[0] or 0, labels.select("comp").distinct().count(), forest.count(), grow, grow <= 1.5 * g.n / p.log_floor, amiss)]
        one = spark.createDataFrame(row, "graph string, n long, samples long, messages long, components long, forest_edges long, growable long, growable_ok boolean, amiss long")
        out = one if out is None else out.unionByName(one)
    return out


_AFTER = "SELECT '{g}' AS graph, n, m AS samples, (SELECT count(*) FROM msg) AS messages, (SELECT count(DISTINCT comp) FROM lab) AS components, n - (SELECT count(DISTINCT comp) FROM lab) AS forest_edges, (SELECT count(*) FROM gr) AS growable, (SELECT count(*) FROM gr) <= 1.5 * n / l AS growable_ok, 0::BIGINT AS amiss FROM q"
add("contract_verdict", contract_verdict, " UNION ALL ".join(_twin(g, _AFTER.format(g=g)) for g in ("order_chain", "order_path", "conv_chain")))
KNOBS = ((1, None, None), (4, None, None), (16, None, None), (64, None, None), (16, 0.5, None), (16, 0.5, 0.05), (16, None, 0.0))


def contract_knobs(spark: SparkSession, d: str) -> DataFrame:
    """Growable components left on the order chain by number of samples, leaders and edge probability; without leaders."""
    rows = []
    for k, (m, pe, pl) in enumerate(KNOBS):
        options = {"num_samples": m} | ({"p_edge": pe} if pe else {}) | ({"p_leader": pl} if pl is not None else {})
        g, p, (labels, _, _) = _contracted(spark, d, "order_chain", **options)
        rows.append((k, m, round(p.p_edge, 9), round(p.p_leader, 9), graphs.growable(labels, g.edges).count(), round(g.n / p.log_floor, 6)))
    return spark.createDataFrame(rows, "k int, num_samples int, p_edge double, p_leader double, growable long, n_over_l double")


add(
    "contract_knobs",
    contract_knobs,
    " UNION ALL ".join(
        _twin("order_chain", f"SELECT {k} AS k, {m} AS num_samples, round(pe, 9)::DOUBLE AS p_edge, round(pl, 9)::DOUBLE AS p_leader, (SELECT count(*) FROM gr) AS growable, round(n / l, 6) AS n_over_l FROM q", m=str(m), **({"pe": f"{pe}::DOUBLE"} if pe else {}), **({"pl": f"{pl}::DOUBLE"} if pl is not None else {}))
        for k, (m, pe, pl) in enumerate(KNOBS)
    ),
)


def labels_only(spark: SparkSession, d: str) -> DataFrame:
    """The variant without forests: vertices take the least leader of any sample component of theirs."""
    _, _, (labels, _, _) = _contracted(spark, d, "conv_chain", labels_only=True)
    return labels.select("vid", "comp")


add(
    "contract_labels_only",
    labels_only,
    f"WITH RECURSIVE {twins.contraction(EDGES['conv_chain'], VERTICES['conv_chain'], 1)}, w2 AS (SELECT sample, comp, min(v) AS leader FROM msg JOIN ld ON v = vid GROUP BY sample, comp), o AS (SELECT v AS vid, min(leader) AS leader FROM msg JOIN w2 USING (sample, comp) GROUP BY v) "
    "SELECT v.vid, CASE WHEN ld.vid IS NOT NULL THEN v.vid ELSE coalesce(leader, v.vid) END AS comp FROM v LEFT JOIN ld USING (vid) LEFT JOIN o ON v.vid = o.vid",
)


def vertex_classes(spark: SparkSession, d: str) -> DataFrame:
    """Per graph: vertices by class, bad ones, alpha ones without a leader (none), bad ones that aren't gamma (none)."""
    out = None
    for name in ("order_chain", "conv_chain"):
        g, p, (labels, _, messages) = _contracted(spark, d, name)
        c = analysis.classify_vertices(g, messages, labels, p, portable=True)
        one = c.agg(
            F.lit(name).alias("graph"), F.count(F.lit(1)).alias("n"), *(F.count_if(F.col("class") == k).alias(k) for k in ("alpha", "beta", "gamma")), F.count_if("bad").alias("bad"),
            F.count_if((F.col("class") == "alpha") & ~F.col("has_leader")).alias("alpha_without_leader"), F.count_if(F.col("bad") & (F.col("class") != "gamma")).alias("bad_not_gamma"),
        )
        out = one if out is None else out.unionByName(one)
    return out


_CLASSES = "SELECT '{g}' AS graph, count(*) AS n, count(*) FILTER (WHERE class = 'alpha') AS alpha, count(*) FILTER (WHERE class = 'beta') AS beta, count(*) FILTER (WHERE class = 'gamma') AS gamma, count(*) FILTER (WHERE bad) AS bad, count(*) FILTER (WHERE class = 'alpha' AND NOT has_leader) AS alpha_without_leader, count(*) FILTER (WHERE bad AND class <> 'gamma') AS bad_not_gamma FROM kls"
add("vertex_classes", vertex_classes, " UNION ALL ".join(_twin(g, _CLASSES.format(g=g), more=", " + twins.classes()) for g in ("order_chain", "conv_chain")))


def small_recovered(spark: SparkSession, d: str) -> DataFrame:
    """Small true components of the conversations: recovered exactly or given a leader."""
    g, p, (labels, _, _) = _contracted(spark, d, "conv_chain", num_samples=64, p_edge=0.5)
    true_ = connectivity.connected_components(g).labels.withColumnRenamed("comp", "t")
    small = true_.groupBy("t").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") <= 3)
    led = labels.withColumn("lead", coin(p.seed, "leader", "vid", portable=True) < p.p_leader).groupBy("comp").agg(F.max("lead").alias("lead"))
    seen = true_.join(small, "t").join(labels, "vid").join(led, "comp").groupBy("t").agg(F.count_distinct("comp").alias("parts"), F.min("lead").alias("lead"))
    return seen.agg(F.count(F.lit(1)).alias("small"), F.count_if((F.col("parts") == 1) | F.col("lead")).alias("recovered"))


add(
    "small_recovered",
    small_recovered,
    _twin(
        "conv_chain",
        "SELECT count(*) AS small, count(*) FILTER (WHERE parts = 1 OR lead) AS recovered FROM (SELECT t, count(DISTINCT comp) AS parts, bool_and(has_leader) AS lead FROM (SELECT vid, vid // 10000 AS t, count(*) OVER (PARTITION BY vid // 10000) AS turns FROM v) JOIN lab USING (vid) JOIN fin USING (comp) WHERE turns <= 3 GROUP BY t)",
        more=", " + twins.classes(), m="64", pe="0.5::DOUBLE",
    )[1:-1],
)


def success_over_seeds(spark: SparkSession, d: str) -> DataFrame:
    """By seed: growable components after one contraction of the conversations, n / L, and whether 1.5 n / L holds; the
    share of seeds that hold is the measured probability of success."""
    rows = []
    for seed in range(1, 9):
        g, p, (labels, _, _) = _contracted(spark, d, "conv_chain", seed=seed)
        grow = graphs.growable(labels, g.edges).count()
        rows.append((seed, grow, round(g.n / p.log_floor, 6), grow <= 1.5 * g.n / p.log_floor))
    return spark.createDataFrame(rows, "seed int, growable long, n_over_l double, success boolean")


add("success_over_seeds", success_over_seeds, " UNION ALL ".join(_twin("conv_chain", f"SELECT {k} AS seed, (SELECT count(*) FROM gr) AS growable, round(n / l, 6) AS n_over_l, (SELECT count(*) FROM gr) <= 1.5 * n / l AS success FROM q", k) for k in range(1, 9)))


def method_log(spark: SparkSession, d: str) -> DataFrame:
    """What the whole method did by default on each graph: samples taken, and sketch phases of both parts."""
    rows = []
    for name in ("part_supplier", "order_part", "order_chain", "order_path", "conv_chain", "doc_line_all", "page_link"):
        log: dict = {}
        n = connectivity.connected_components(derive.GRAPHS[name](spark, d), log=log).labels.select("comp").distinct().count()
        rows.append((name, log["n"], n, log["samples"] if log["contracted"] else 0, len(log["phases_a"]), len(log["phases_b"]), sum(x["recovered"] for x in log["phases_a"] + log["phases_b"])))
    return spark.createDataFrame(rows, "graph string, n long, components long, samples int, sketch_phases_a int, sketch_phases_b int, recovered long")


add("cc_method_log", method_log)


def tree_hits(spark: SparkSession, d: str) -> DataFrame:
    """Chains of k vertices that lie whole in a sample, against 1 - (1 - p^(k-1))^m."""
    g = derive.order_chain(spark, d)
    m, p = 16, 0.5
    samples = cut(sampling.sample_edges(g.edges, m, p, 3, portable=True))
    o = read_table(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]).withColumn("r", F.row_number().over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")))
    out = None
    for k in (2, 3, 4):
        chain = o.withColumn("chain", F.concat_ws(".", "o_custkey", F.floor((F.col("r") - 1) / k)))
        e = chain.select("chain", F.col("o_orderkey").alias("a"), F.lead("o_orderkey").over(W.partitionBy("chain").orderBy("r")).alias("b")).where("b IS NOT NULL").select("chain", F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))
        full = e.join(e.groupBy("chain").count().where(F.col("count") == k - 1).select("chain"), "chain")
        expect = 1 - (1 - p ** (k - 1)) ** m
        one = analysis.tree_hit_rate(samples, full, k).select(F.lit(k).alias("k"), "chains", "hit", (F.abs(F.col("rate") - expect) < 0.05).alias("rate_ok"))
        out = one if out is None else out.unionByName(one)
    return out


add(
    "tree_hit_rate",
    tree_hits,
    " UNION ALL ".join(
        f"""SELECT {k} AS k, count(*) AS chains, count(*) FILTER (WHERE hit) AS hit, abs(count(*) FILTER (WHERE hit) / count(*) - {1 - (1 - 0.5 ** (k - 1)) ** 16}) < 0.05 AS rate_ok FROM (
SELECT chain, bool_or(have = {k - 1}) AS hit FROM (SELECT chain, sample, count(*) FILTER (WHERE {twins.coin(3, "sample", "sample", "src", "dst")} < 0.5) AS have FROM (
SELECT chain, least(a, b) AS src, greatest(a, b) AS dst, unnest(range(1, 17)) AS sample FROM (SELECT chain, a, b, count(b) OVER (PARTITION BY chain) AS m FROM (
SELECT chain, o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY chain ORDER BY r) AS b FROM (
SELECT o_orderkey, r, o_custkey || '.' || ((r - 1) // {k}) AS chain FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS r FROM orders)))) WHERE b IS NOT NULL AND m = {k - 1})
GROUP BY chain, sample) GROUP BY chain)"""
        for k in (2, 3, 4)
    ),
)


# sketches and the whole method


def sketch_finish(spark: SparkSession, d: str) -> DataFrame:
    log: list = []
    g = derive.order_chain(spark, d)
    done = baselines.sketch_only_cc(g, log)
    return analysis.forest_checks(g, done)


add("sketch_finish_verdict", sketch_finish, with_cc("order_chain", "SELECT count(*) AS n, count(DISTINCT comp) AS components, count(*) - count(DISTINCT comp) AS forest_edges, true AS size_ok, true AS inside_ok, true AS spans_ok FROM c"))


def sketch_phases(spark: SparkSession, d: str) -> DataFrame:
    log: list = []
    baselines.sketch_only_cc(derive.order_chain(spark, d), log)
    return spark.createDataFrame([(x["phase"], x["growable"], x["recovered"]) for x in log], "phase int, growable long, recovered long")


add("sketch_phases", sketch_phases)


def hub_gadget(spark: SparkSession, d: str) -> DataFrame:
    """The planted graph on which both stages leave growable awake components, so that the sketches must finish."""
    g = graphs.hub_gadget(spark, 50)
    split = sparsify.sparsify_by_degree(g, 3)
    left = split.labels.select("comp").distinct().count()
    done = connectivity.connected_components(g, exact_below=0)
    return done.labels.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("comp").alias("components")).withColumns({"after_stage2": F.lit(left).cast("long"), "forest_edges": F.lit(done.forest.distinct().count()).cast("long")})


add("finish_hub_gadget", hub_gadget, "SELECT 1800 AS n, 1 AS components, 51 AS after_stage2, 1799 AS forest_edges")


def union_rule(spark: SparkSession, d: str, graph: str = "doc_line") -> DataFrame:
    g = derive.GRAPHS[graph](spark, d)
    half = coin(7, "half", "src", "dst") < 0.5
    one, two = (connectivity.connected_components(graphs.EdgeSet(g.vertices, g.edges.where(c))) for c in (half, ~half))
    return connectivity.merge_results(g.vertices, one.forest, two.forest).labels


add("merge_union_rule", union_rule, with_cc("doc_line", "SELECT vid, comp FROM c"))
add("cc_reuse_asleep", lambda spark, d: connectivity.connected_components(derive.doc_line(spark, d), reuse_asleep_edges=True).labels, with_cc("doc_line", "SELECT vid, comp FROM c"))
add("merge_union_rule_all_lines", lambda spark, d: union_rule(spark, d, "doc_line_all"), with_cc("doc_line_all", "SELECT vid, comp FROM c"))
add("cc_reuse_asleep_all_lines", lambda spark, d: connectivity.connected_components(derive.doc_line_all(spark, d), reuse_asleep_edges=True).labels, with_cc("doc_line_all", "SELECT vid, comp FROM c"))


SIZED = (("customer", "c_custkey"), ("orders", "o_orderkey"), ("lineitem", "l_partkey"), ("events", "event_id"))


def params_table(spark: SparkSession, d: str) -> DataFrame:
    """The method's own parameters for as many vertices as some tables have keys."""
    counts = [(t, read_table(spark, d, t, [k]).agg(F.count_distinct(k)).first()[0]) for t, k in SIZED]
    rows = [(t, n, p.s, p.num_samples, round(p.log_floor, 6), round(p.small, 6)) for t, n in counts for p in [params_for(n, faithful=True)]]
    return spark.createDataFrame(rows, "source string, n long, s int, num_samples int, log_floor double, small double")


_KEYS = " UNION ALL ".join(f"SELECT '{t}' AS source, count(DISTINCT {k}) AS n FROM {t}" for t, k in SIZED)
add("params_table", params_table, f"SELECT source, n, greatest(2, ceil(l))::INTEGER AS s, ceil(sqrt(n))::INTEGER AS num_samples, round(l, 6) AS log_floor, round(sqrt(log2(n)), 6) AS small FROM (SELECT source, n, greatest(2.0, log2(log2(n))) AS l FROM ({_KEYS}))")


# minimum spanning forests

_LINE = "SELECT least(a, b) AS src, greatest(a, b) AS dst, w AS weight FROM (SELECT s_suppkey AS a, lead(s_suppkey) OVER o AS b, abs(s_acctbal - lead(s_acctbal) OVER o) AS w FROM supplier WINDOW o AS (ORDER BY s_acctbal, s_suppkey)) WHERE b IS NOT NULL"
_ROUND = ["src", "dst", "round(weight, 6) AS weight"]
add("msf_supplier_line", lambda spark, d: msf.minimum_spanning_forest(derive.supplier_steps(spark, d)).selectExpr(*_ROUND), f"SELECT src, dst, round(weight, 6) AS weight FROM ({_LINE})")


EDGES["embeddings"] = "SELECT a.vec_id AS src, b.vec_id AS dst, round(1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS weight FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id"
FORESTS = {"part_supplier": derive.part_supplier, "user_hour": derive.user_hour_pairs, "embeddings": derive.embedding_pairs}


def _msf(graph, method):
    return lambda spark, d: method(graph(spark, d)).selectExpr(*_ROUND)


for _name, _graph in FORESTS.items():
    add(f"msf_{_name}", _msf(_graph, msf.minimum_spanning_forest), twins.spanning_forest(EDGES[_name]))
    add(f"msf_sequential_{_name}", _msf(_graph, lambda g: msf.minimum_spanning_forest(g, method="sequential")), twins.spanning_forest(EDGES[_name]))
    add(f"baseline_hook_and_contract_msf_{_name}", _msf(_graph, msf.hook_and_contract_msf), twins.spanning_forest(EDGES[_name]))
add("msf_uniform_runs", _msf(derive.supplier_levels, lambda g: msf.with_weights(msf.bucketed_forest(g, "uniform"), g.edges)), twins.spanning_forest(EDGES["supplier_line"]))
add("baseline_hook_and_contract_msf", QUERIES["baseline_hook_and_contract_msf_part_supplier"], SQL["msf_part_supplier"])
add("baseline_squared_growth_msf", _msf(derive.user_hour, lambda g: msf.squared_growth_msf(g)[0]), SQL["msf_user_hour"])


def msf_instances(spark: SparkSession, d: str) -> DataFrame:
    """How many nested instances each forest took at once, and the edges before and after the filter.  The forests have
    many small jobs each and nothing in common, so they are made side by side."""

    def one(name: str, graph) -> tuple:
        log: dict = {}
        out = msf.minimum_spanning_forest(graph(spark, d), log=log).count()
        return name, out, log["instances"], log.get("thin"), log.get("light")

    with ThreadPoolExecutor(len(FORESTS)) as pool:
        rows = list(pool.map(inheritable_thread_target(spark)(one), FORESTS, FORESTS.values()))
    return spark.createDataFrame(rows, "graph string, forest_edges long, instances array<int>, thin long, light long")


add("msf_instances", msf_instances)


def thin_and_light(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name, graph in (("user_hour", derive.user_hour), ("supplier_line", derive.supplier_line)):
        log: dict = {}
        msf.minimum_spanning_forest(graph(spark, d), faithful=True, force_filter=True, log=log)
        portable = msf.thin_by_sampling(graph(spark, d), log["p"], 1, portable=True).count()
        one = spark.createDataFrame([(name, log["n"], log["edges"], portable, log["light"] <= 3 * log["n"] / log["p"])], "graph string, n long, edges long, thin long, light_ok boolean")
        out = one if out is None else out.unionByName(one)
    return out


add("thin_and_light_verdict", thin_and_light, " UNION ALL ".join(f"SELECT '{g}' AS graph, n, count(*) AS edges, count(*) FILTER (WHERE {twins.coin(1, 'thin', 'src', 'dst')} < 1 / sqrt(n)) AS thin, true AS light_ok FROM ({EDGES[g]}), (SELECT count(*) AS n FROM ({VERTICES[g]})) GROUP BY n" for g in ("user_hour", "supplier_line")))


# nested instances


def _nested(spark: SparkSession, d: str):
    g = derive.supplier_line(spark, d).settle()
    e = cut(msf.nested_instances(g.edges, g.n))
    return g, e, e.agg(F.max("first_instance")).first()[0]


_RANK = f"SELECT src, dst, weight, rank, ((rank - 1) // n + 1)::INTEGER AS first_instance FROM (SELECT src, dst, weight, row_number() OVER (ORDER BY weight, src, dst) AS rank, (SELECT count(*) FROM supplier) AS n FROM ({EDGES['supplier_line']}))"
add("nested_buckets", lambda spark, d: _nested(spark, d)[1].groupBy("first_instance").agg(F.count(F.lit(1)).alias("edges"), F.round(F.max("weight"), 6).alias("heaviest")), f"SELECT first_instance, count(*) AS edges, round(max(weight), 6) AS heaviest FROM ({_RANK}) GROUP BY 1")
add("global_rank", lambda spark, d: _nested(spark, d)[1].select("src", "dst", "rank"), f"SELECT src, dst, rank FROM ({_RANK})")


def nested_labels(spark: SparkSession, d: str, most: int | None = 6) -> DataFrame:
    """Components of the first instances (None: all), by the incremental and by the parallel way: equal, and their number."""
    g, e, k = _nested(spark, d)
    k = k if most is None else min(k, most)
    one = cut(nested.components_of_nested(e, g.vertices, k, "incremental").groupBy("instance", "comp").agg(F.count(F.lit(1)).alias("size")).groupBy("instance").agg(F.count(F.lit(1)).alias("components"), F.max("size").alias("largest")))
    two = nested.components_of_nested(e.where(F.col("first_instance") <= k), g.vertices, k, "parallel").groupBy("instance", "comp").agg(F.count(F.lit(1)).alias("size")).groupBy("instance").agg(F.count(F.lit(1)).alias("components2"), F.max("size").alias("largest2"))
    return one.join(two, "instance").select("instance", "components", "largest", ((F.col("components") == F.col("components2")) & (F.col("largest") == F.col("largest2"))).alias("same"))


add("nested_labels", nested_labels, " UNION ALL ".join(f"(WITH RECURSIVE e AS (SELECT src, dst FROM ({_RANK}) WHERE first_instance <= {i}), s AS (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e), c(vid, comp) USING KEY (vid) AS (SELECT s_suppkey, s_suppkey FROM supplier UNION (SELECT s.b AS vid, min(c.comp) AS comp FROM c JOIN s ON c.vid = s.a JOIN recurring.c k ON k.vid = s.b WHERE c.comp < k.comp GROUP BY s.b)) SELECT {i}::INTEGER AS instance, count(*) AS components, max(n) AS largest, true AS same FROM (SELECT comp, count(*) AS n FROM c GROUP BY comp) HAVING {i} <= (SELECT max(first_instance) FROM ({_RANK})))" for i in range(1, 7)))

_ALL = f"r AS MATERIALIZED ({_RANK}), i AS (SELECT unnest(range(1, (SELECT max(first_instance) FROM r) + 1))::INTEGER AS i)"
add("nested_labels_all", lambda spark, d: nested_labels(spark, d, None), f"WITH RECURSIVE {_ALL}, e AS (SELECT i, src, dst FROM r JOIN i ON first_instance <= i), s AS (SELECT i, src AS a, dst AS b FROM e UNION ALL SELECT i, dst, src FROM e), c(i, vid, comp) USING KEY (i, vid) AS (SELECT i, s_suppkey, s_suppkey FROM supplier, i UNION (SELECT s.i, s.b AS vid, min(c.comp) AS comp FROM c JOIN s ON c.i = s.i AND c.vid = s.a JOIN recurring.c k ON k.i = s.i AND k.vid = s.b WHERE c.comp < k.comp GROUP BY s.i, s.b)) SELECT i AS instance, count(*) AS components, max(n) AS largest, true AS same FROM (SELECT i, comp, count(*) AS n FROM c GROUP BY i, comp) GROUP BY i")


def nested_kruskal(spark: SparkSession, d: str) -> DataFrame:
    g, e, k = _nested(spark, d)
    labels = nested.components_of_nested(e, g.vertices, k)
    return msf.with_weights(nested.bucket_kruskal(e, cut(labels)), g.edges).selectExpr(*_ROUND)


add("nested_bucket_kruskal", nested_kruskal, SQL["msf_supplier_line"])
add("nested_encoding", lambda spark, d: nested.decode(nested.encode_nested(_nested(spark, d)[1]), 3), f"SELECT src, dst FROM ({_RANK}) WHERE first_instance <= 3")
add("nested_encoding_all", lambda spark, d: (lambda t: nested.decode_all(nested.encode_nested(t[1]), t[2]))(_nested(spark, d)), f"WITH {_ALL} SELECT i AS instance, src, dst FROM r JOIN i ON first_instance <= i")
add("nested_message_total", lambda spark, d: (lambda t: ledger.nested_message_total(t[1], t[2]))(_nested(spark, d)), f"SELECT sum((m - first_instance + 1) * 2)::BIGINT AS messages FROM ({_RANK}), (SELECT max(first_instance) AS m FROM ({_RANK}))")


def nested_sparse(spark: SparkSession, d: str, most: int | None = 6) -> DataFrame:
    """Sparsification of the first instances (None: all) side by side keeps its guarantees."""
    g, e, k = _nested(spark, d)
    k = k if most is None else most
    unfolded = e.agg(F.sum(F.greatest(F.lit(0), F.lit(k + 1) - F.col("first_instance")))).first()[0] or 0
    if nested.UNFOLD_LIMIT < unfolded and e.count() <= sampling.SAMPLE_LIMIT:  # all instances in tasks, one at a time
        measures = nested.nested_split_measures(e, g.vertices, k, 3)
        return measures.select("count_ok", "size_ok", "degree_ok", (F.col("edges_a") + F.col("edges_b")).alias("edges"))
    union, split = nested.nested_sparsify(e.where(F.col("first_instance") <= k), g.vertices, k, 3)
    return analysis.split_measures(union, split, 3).select("count_ok", "size_ok", "degree_ok", (F.col("edges_a") + F.col("edges_b")).alias("edges"))


add("nested_sparsify", nested_sparse, f"SELECT true AS count_ok, true AS size_ok, true AS degree_ok, sum(7 - first_instance)::BIGINT AS edges FROM ({_RANK}) WHERE first_instance <= 6")
add("nested_sparsify_all", lambda spark, d: nested_sparse(spark, d, None), f"WITH {_ALL} SELECT true AS count_ok, true AS size_ok, true AS degree_ok, sum((SELECT max(i) FROM i) + 1 - first_instance)::BIGINT AS edges FROM r")


def nested_contracted(spark: SparkSession, d: str) -> DataFrame:
    """Contraction and finish of three chained instances side by side."""
    chain = derive.order_chain(spark, d)
    e = chain.edges.withColumn("first_instance", (F.floor(coin(5, "run", "src", "dst") * 3) + 1).cast("int"))
    union = graphs.disjoint_union(cut(nested.expanded(e, 3)), chain.vertices, 3)
    union = union.settle()
    labels, forest = nested.nested_contract(union, params_for(union.n, seed=2))
    done = nested.nested_finish(union, labels, cut(forest))
    last = done.labels.where(F.floor(F.col("vid") / nested.SHIFT) == 3)
    return canonical_labels(last.select("vid"), last).select((F.col("vid") % nested.SHIFT).alias("vid"), (F.col("comp") % nested.SHIFT).alias("comp"))


add("nested_contract_and_finish", nested_contracted, with_cc("order_chain", "SELECT vid, comp FROM c"))


def proxy_plan(spark: SparkSession, d: str) -> DataFrame:
    g = derive.part_supplier(spark, d)
    return nested.assign_proxies(graphs.degrees(g), g.n)


_DEG = f"WITH e AS ({EDGES['part_supplier']}), g AS (SELECT v AS vid, count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v), n AS (SELECT count(*) AS n FROM g)"
add("proxy_plan", proxy_plan, f"{_DEG} SELECT vid, d, p AS proxies, (sum(p) OVER (ORDER BY vid) - p)::BIGINT AS first_proxy, least(ceil(sqrt(n)), ceil(n / d))::BIGINT AS per_proxy FROM (SELECT vid, d, n, ceil(d / ceil(sqrt(n)))::BIGINT AS p FROM g, n)")


def proxy_load(spark: SparkSession, d: str) -> DataFrame:
    g = derive.part_supplier(spark, d)
    n = g.n
    proxies = cut(nested.assign_proxies(graphs.degrees(g), n))
    edges = g.edges.withColumn("first_instance", F.lit(1))
    load = nested.deliver_to_proxies(nested.encode_nested(edges), proxies)
    total = proxies.agg(F.sum("proxies").cast("long").alias("proxies"), F.min(F.col("proxies") * F.col("per_proxy")).alias("served"))
    naive = baselines.naive_nested_load(graphs.degrees(g), n)
    return load.agg(F.sum("received").cast("long").alias("delivered"), (F.max("received") <= 3 * math.ceil(n**0.5)).alias("load_ok")).join(total).join(naive).select("delivered", "load_ok", "proxies", (F.col("served") >= F.lit(math.ceil(n**0.5))).alias("served_ok"), "overloaded")


add("proxy_load", proxy_load, f"{_DEG} SELECT (SELECT 2 * count(*) FROM e) AS delivered, true AS load_ok, (SELECT sum(ceil(d / ceil(sqrt(n))))::BIGINT FROM g, n) AS proxies, true AS served_ok, (SELECT max(d) * ceil(sqrt(any_value(n))) > any_value(n) FROM g, n) AS overloaded")


def routing(spark: SparkSession, d: str) -> DataFrame:
    m = graphs.symmetrize(derive.order_part(spark, d).edges).select(F.col("u").alias("sender"), F.col("v").alias("receiver"))
    return nested.routing_feasible(m, 1000, 0.05)


add("routing_audit", routing, f"WITH e AS ({EDGES['order_part']}), d AS (SELECT v, count(*) AS k FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v) SELECT max(k) AS max_sent, max(k) AS max_received, max(k) <= 50 AS feasible FROM d")


def schedule(spark: SparkSession, d: str) -> DataFrame:
    """The messages of the order-part graph in the rounds of the schedule, where a vertex's auxiliary node is the
    remainder of the other end's key: messages of each round, and the most that a vertex sends and receives in it."""
    c = 4
    rounds = spark.createDataFrame(nested.auxiliary_schedule(c), "a int, b int")
    m = derive.order_part(spark, d).edges.select(F.col("src").alias("sender"), F.col("dst").alias("receiver"), (F.col("dst") % c).cast("int").alias("a"), (F.col("src") % c).cast("int").alias("b"))
    sent = m.groupBy("a", "b", "sender").agg(F.count(F.lit(1)).alias("k")).groupBy("a", "b").agg(F.sum("k").alias("messages"), F.max("k").alias("max_sent"))
    got = m.groupBy("a", "b", "receiver").agg(F.count(F.lit(1)).alias("k")).groupBy("a", "b").agg(F.max("k").alias("max_received"))
    return rounds.join(sent, ["a", "b"], "left").join(got, ["a", "b"], "left").select("a", "b", *(F.coalesce(x, F.lit(0)).alias(x) for x in ("messages", "max_sent", "max_received")))


add(
    "auxiliary_schedule",
    schedule,
    f"""WITH m AS MATERIALIZED (SELECT src, dst, dst % 4 AS a, src % 4 AS b FROM ({EDGES['order_part']})), s AS (SELECT a, b, max(k) AS k FROM (SELECT a, b, count(*) AS k FROM m GROUP BY a, b, src) GROUP BY a, b), r AS (SELECT a, b, max(k) AS k FROM (SELECT a, b, count(*) AS k FROM m GROUP BY a, b, dst) GROUP BY a, b),
t AS (SELECT a, b, count(*) AS k FROM m GROUP BY a, b) SELECT x.a::INTEGER AS a, y.b::INTEGER AS b, coalesce(t.k, 0) AS messages, coalesce(s.k, 0) AS max_sent, coalesce(r.k, 0) AS max_received FROM range(4) x(a) CROSS JOIN range(4) y(b) LEFT JOIN t ON t.a = x.a AND t.b = y.b LEFT JOIN s ON s.a = x.a AND s.b = y.b LEFT JOIN r ON r.a = x.a AND r.b = y.b""",
)


def ledger_sparsify(spark: SparkSession, d: str) -> DataFrame:
    """Messages of the seven steps on the order-part graph; as broadcasts, where a payload counts once however many read
    it; and lean, where only what a neighbour doesn't know yet is sent."""
    g = derive.order_part(spark, d).settle()
    return ledger.sparsify_ledger(g, sparsify.sparsify_by_degree(g, params_for(g.n).s))


add(
    "ledger_sparsify",
    ledger_sparsify,
    f"""WITH RECURSIVE {twins.degree_split(EDGES["order_part"], "SELECT NULL::BIGINT AS vid WHERE false")},
k AS (SELECT n, (SELECT count(*) FROM e) AS m, (SELECT count(*) FROM h1) AS k1, (SELECT count(*) FROM h2) AS k2, (SELECT count(*) FROM y JOIN c1 f ON y.a = f.vid WHERE f.comp <> f.vid) AS told, (SELECT count(*) FROM y JOIN fin f ON y.a = f.vid WHERE f.awake) AS up FROM p)
SELECT step, 1::BIGINT AS rounds, messages, broadcasts, lean FROM k, LATERAL (VALUES ('announce_degree', 2 * m, n, 2 * m), ('stage1_choice', k1, k1, k1), ('stage1_labels', n, n, n), ('announce_labels', 2 * m, n, told), ('stage2_choice', k2, k2, k2), ('stage2_labels', n, n, n), ('announce_awake', 2 * m, n, up)) t(step, messages, broadcasts, lean)""",
)


def ledger_contract(spark: SparkSession, d: str) -> DataFrame:
    g, p, (_, _, messages) = _contracted(spark, d, "order_chain")
    samples = sampling.sample_edges(g.edges, p.num_samples, p.p_edge, p.seed, portable=True)
    return ledger.contract_ledger(samples, sampling.choose_leaders(g.vertices, p.p_leader, p.seed, portable=True), messages, p.num_samples)


add(
    "ledger_contract",
    ledger_contract,
    _twin(
        "order_chain",
        """SELECT 'edges_to_bosses' AS step, 1 AS rounds, (SELECT count(*) FROM s) AS messages, (SELECT max(k) FROM (SELECT count(*) AS k FROM s GROUP BY src)) AS max_sent, (SELECT max(k) FROM (SELECT count(*) AS k FROM s GROUP BY sample)) AS max_received
UNION ALL SELECT 'leader_flags', 1, (SELECT count(*) FROM ld) * m, m, (SELECT count(*) FROM ld) FROM q
UNION ALL SELECT 'replies', 1, (SELECT count(*) FROM msg), (SELECT max(k) FROM (SELECT count(*) AS k FROM msg GROUP BY sample)), (SELECT max(k) FROM (SELECT count(*) AS k FROM msg GROUP BY v))
UNION ALL SELECT 'pointers', 1, count(DISTINCT v), 1, count(DISTINCT v) FROM msg WHERE hop IS NOT NULL""",
    )[1:-1],
)


def pieces(spark: SparkSession, d: str) -> DataFrame:
    """Almost-partition of the order path and the order-part forest: sizes, coverage and shared vertices."""
    out = None
    for name, s in (("order_path", 4), ("order_part", 5)):
        labels, forest = complete_partition(as_links(derive.GRAPHS[name](spark, d).edges))
        p = cut(analysis.almost_partition(forest, labels, s))
        per = p.groupBy("comp", "piece").agg(F.count(F.lit(1)).alias("size"), F.count_if(~F.col("is_unique")).alias("shared"))
        one = per.agg(F.lit(name).alias("graph"), (F.min("size") >= s).alias("least_ok"), (F.max("size") <= 3 * s).alias("most_ok"), (F.max("shared") <= 1).alias("shared_ok"), F.lit(p.select("vid").distinct().count()).alias("covered"))
        out = one if out is None else out.unionByName(one)
    return out


add("almost_partition_verdict", pieces, f"SELECT 'order_path' AS graph, true AS least_ok, true AS most_ok, true AS shared_ok, count(*) AS covered FROM orders UNION ALL SELECT 'order_part', true, true, true, (SELECT count(DISTINCT l_partkey) + count(DISTINCT l_orderkey) FROM lineitem)")


def bad_bound(spark: SparkSession, d: str) -> DataFrame:
    """Bad vertices of the order chain against the bound that the pieces give."""
    g, p, (labels, _, messages) = _contracted(spark, d, "order_path")
    done = baselines.exact_local_cc(g)
    c = cut(analysis.classify_vertices(g, messages, labels, p, portable=True))
    tiles = cut(analysis.almost_partition(done.forest, done.labels, max(2, round(p.small))))
    bound = analysis.piece_bad_bound(tiles, cut(sampling.sample_edges(g.edges, p.num_samples, p.p_edge, p.seed, portable=True)), done.forest, c)
    return bound.agg(F.sum("adds").alias("bound")).join(c.agg(F.count_if("bad").alias("bad"))).select((F.col("bad") <= F.col("bound")).alias("bound_ok"))


add("bad_vertex_bound", bad_bound, "SELECT true AS bound_ok")


# reductions

for _g, _yes in (("part_supplier", "true"), ("customer_order", "true"), ("geo_tree", "true"), ("user_hour", "NOT EXISTS (SELECT 1 FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst)")):
    add(f"bipartite_{_g}", (lambda g: lambda spark, d: reductions.bipartite_components(derive.GRAPHS[g](spark, d)))(_g), with_cc(_g, f"SELECT comp, count(*) AS size, {_yes} AS bipartite FROM c GROUP BY comp"))


def cut_nation(spark: SparkSession, d: str) -> DataFrame:
    g = derive.geo_tree(spark, d)
    return reductions.is_cut(g, g.edges.where((F.col("src") == T[9] + 3) | (F.col("dst") == T[9] + 3)))


add("cut_geo_nation", cut_nation, f"SELECT r AS before, r + 1 + s + c AS after, true AS is_cut FROM (SELECT count(DISTINCT n_regionkey) AS r FROM nation), (SELECT count(*) AS s FROM supplier WHERE s_nationkey = 3), (SELECT count(*) AS c FROM customer WHERE c_nationkey = 3)")


def pairs(spark: SparkSession, d: str) -> DataFrame:
    g = derive.order_chain(spark, d)
    o = read_table(spark, d, "orders", ["o_orderkey"])
    return reductions.st_connected(connectivity.connected_components(g), o.select(F.col("o_orderkey").alias("s"), (F.col("o_orderkey") + 7).alias("t")).join(o.select(F.col("o_orderkey").alias("t")), "t", "left_semi"))


add("st_pairs", pairs, "SELECT a.o_orderkey AS s, b.o_orderkey AS t, a.o_custkey = b.o_custkey AS connected FROM orders a JOIN orders b ON b.o_orderkey = a.o_orderkey + 7")
for _g in ("geo_tree", "page_link", "doc_line", "doc_line_all"):
    add(f"cycle_{_g}", (lambda g: lambda spark, d: reductions.has_cycle(derive.GRAPHS[g](spark, d)))(_g), with_cc(_g, "SELECT a.comp, coalesce(m, 0) > size - 1 AS has_cycle FROM (SELECT comp, count(*) AS size FROM c GROUP BY comp) a LEFT JOIN (SELECT comp, count(*) AS m FROM e JOIN c ON e.src = c.vid GROUP BY comp) b ON a.comp = b.comp"))


def on_cycle(spark: SparkSession, d: str) -> DataFrame:
    g = derive.geo_tree(spark, d)
    e = g.edges.orderBy("src", "dst").first()
    return spark.createDataFrame([(reductions.edge_on_cycle(g, e["src"], e["dst"]),)], "on_cycle boolean")


add("edge_on_cycle", on_cycle, "SELECT false AS on_cycle")


# baselines

for _b, _f in (("star_contraction", baselines.star_contraction_cc), ("hook_and_contract", baselines.hook_and_contract_cc), ("sketch_only", baselines.sketch_only_cc), ("growth_then_sketch", baselines.growth_then_sketch_cc), ("exact_local", baselines.exact_local_cc)):
    add(f"baseline_{_b}_cc", (lambda f: lambda spark, d: f(derive.doc_line(spark, d)).labels)(_f), with_cc("doc_line", "SELECT vid, comp FROM c"))
    add(f"baseline_{_b}_cc_all_lines", (lambda f: lambda spark, d: f(derive.doc_line_all(spark, d)).labels)(_f), with_cc("doc_line_all", "SELECT vid, comp FROM c"))
add("baseline_label_propagation", lambda spark, d: baselines.min_label_propagation(derive.conv_chain(spark, d))[0], with_cc("conv_chain", "SELECT vid, comp FROM c"))


# relational families


def table(name: str, *columns: str):
    return lambda spark, d: read_table(spark, d, name, list(columns) or None)


def _geo(spark: SparkSession, d: str) -> DataFrame:
    r, n, s = (read_table(spark, d, t) for t in ("region", "nation", "supplier"))
    return rel.checked_broadcast_join(rel.checked_broadcast_join(s, n, s["s_nationkey"] == n["n_nationkey"]), r, n["n_regionkey"] == r["r_regionkey"]).groupBy("r_name").agg(F.count(F.lit(1)).alias("suppliers"), F.round(F.sum("s_acctbal"), 2).alias("balance"))


add("join_star", _geo, "SELECT r_name, count(*) AS suppliers, round(sum(s_acctbal), 2) AS balance FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
add("join_shuffle_hash", lambda spark, d: rel.shuffle_hash_join(read_table(spark, d, "orders", ["o_orderkey", "o_custkey"]), read_table(spark, d, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "o_custkey"), "o_custkey").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
add("join_sort_merge", lambda spark, d: rel.sort_merge_join(read_table(spark, d, "lineitem", ["l_orderkey", "l_quantity"]), read_table(spark, d, "orders", ["o_orderkey", "o_orderstatus"]).withColumnRenamed("o_orderkey", "l_orderkey"), "l_orderkey").groupBy("o_orderstatus").agg(F.sum("l_quantity").alias("q")), "SELECT o_orderstatus, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
add("join_theta", lambda spark, d: derive.supplier_line(spark, d).edges.agg(F.count(F.lit(1)).alias("n"), F.round(F.max("weight"), 6).alias("w")), f"SELECT count(*) AS n, round(max(weight), 6) AS w FROM ({EDGES['supplier_line']})")


def _range(spark: SparkSession, d: str) -> DataFrame:
    bands = spark.range(10).select((F.col("id") * 7 + 1).alias("low"), (F.col("id") * 7 + 9).alias("high"), F.col("id").alias("band"))
    return rel.range_join(read_table(spark, d, "part", ["p_partkey", "p_size"]), "p_size", bands, "low", "high", 8).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


add("join_range", _range, "SELECT id AS band, count(*) AS n FROM part JOIN (SELECT range AS id FROM range(10)) ON p_size BETWEEN id * 7 + 1 AND id * 7 + 9 GROUP BY 1")


def _interval(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts", "event_type"])
    a, b = (e.where(F.col("event_type") == t).select("user_id", F.col("event_id").alias(f"{x}_id"), F.col("ts").alias(f"{x}_ts")) for x, t in (("a", "click"), ("b", "purchase")))
    return rel.interval_join(a, b, "a_ts", "b_ts", 86400, ["user_id"]).select("user_id", "a_id", "b_id")


add("join_interval", _interval, "SELECT a.user_id, a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 86400 SECOND")


def _asof(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts", "event_type", "value"])
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'click'").select(F.col("event_id"), "user_id", "ts", F.col("event_id").alias("click"))
    return rel.asof_join(left, right, "ts", ["user_id"], "click", "event_id").select("event_id", "click")


add("join_asof", _asof, "SELECT p.event_id, (SELECT c.event_id FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND c.ts <= p.ts ORDER BY c.ts DESC, c.event_id DESC LIMIT 1) AS click FROM events p WHERE p.event_type = 'purchase'")
add("join_semi_anti", lambda spark, d: read_table(spark, d, "customer", ["c_custkey"]).join(read_table(spark, d, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey", F.lit(False).alias("ordered")).union(read_table(spark, d, "customer", ["c_custkey"]).join(read_table(spark, d, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", F.lit(True).alias("ordered"))), "SELECT c_custkey, c_custkey IN (SELECT o_custkey FROM orders) AS ordered FROM customer")
add("join_outer", lambda spark, d: read_table(spark, d, "labels", ["doc_id", "quality"]).join(read_table(spark, d, "documents", ["doc_id", "lang"]), "doc_id", "full").groupBy("lang", "quality").agg(F.count(F.lit(1)).alias("n")), "SELECT lang, quality, count(*) AS n FROM labels FULL JOIN documents USING (doc_id) GROUP BY 1, 2")
add("join_salted", lambda spark, d: rel.salted_join(read_table(spark, d, "documents", ["doc_id", "source"]), read_table(spark, d, "documents", ["source", "n_chars"]).groupBy("source").agg(F.sum("n_chars").alias("total")), "source", 8).groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.max("total").alias("total")), "SELECT source, count(*) AS n, sum(n_chars)::BIGINT AS total FROM documents GROUP BY 1")
add("join_cross_grid", lambda spark, d: read_table(spark, d, "region", ["r_regionkey"]).crossJoin(spark.range(3).select(F.col("id").alias("k"))).select("r_regionkey", "k"), "SELECT r_regionkey, range AS k FROM region, range(3)")
add("agg_basic", lambda spark, d: read_table(spark, d, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice"]).groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"), F.round(F.avg("l_extendedprice"), 4).alias("a"), F.max("l_extendedprice").alias("m"), F.round(F.stddev("l_quantity"), 6).alias("s")), "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q, round(avg(l_extendedprice), 4) AS a, max(l_extendedprice) AS m, round(stddev(l_quantity), 6) AS s FROM lineitem GROUP BY 1, 2")
add("agg_best_by", lambda spark, d: rel.best_by(read_table(spark, d, "orders", ["o_custkey", "o_totalprice", "o_orderkey"]), "o_custkey", ["o_totalprice", "o_orderkey"]), "SELECT o_custkey, o_totalprice, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey DESC) = 1")
add("agg_xor_fold", lambda spark, d: read_table(spark, d, "events", ["user_id", "event_id"]).groupBy("user_id").agg(F.bit_xor("event_id").alias("x")), "SELECT user_id, bit_xor(event_id) AS x FROM events GROUP BY 1")
add("agg_distinct", lambda spark, d: read_table(spark, d, "lineitem", ["l_suppkey", "l_partkey"]).groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
add("agg_rollup", lambda spark, d: read_table(spark, d, "part", ["p_brand", "p_type", "p_size"]).rollup("p_brand", "p_type").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level")), "SELECT p_brand, p_type, count(*) AS n, grouping_id(p_brand, p_type)::BIGINT AS level FROM part GROUP BY ROLLUP (p_brand, p_type)")
add("agg_cube", lambda spark, d: read_table(spark, d, "documents", ["lang", "source"]).cube("lang", "source").agg(F.count(F.lit(1)).alias("n")), "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
add("agg_pivot", lambda spark, d: read_table(spark, d, "orders", ["o_orderpriority", "o_orderstatus"]).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("o_orderpriority", *(F.coalesce(x, F.lit(0)).alias(f"s_{x}") for x in "FOP")), "SELECT o_orderpriority, " + ", ".join(f"count(*) FILTER (o_orderstatus = '{x}') AS s_{x}" for x in "FOP") + " FROM orders GROUP BY 1")
add("agg_quantiles", lambda spark, d: read_table(spark, d, "lineitem", ["l_quantity"]).agg(*(F.percentile("l_quantity", q).alias(f"q{int(q * 100)}") for q in (0.25, 0.5, 0.9))), "SELECT quantile_cont(l_quantity, 0.25) AS q25, quantile_cont(l_quantity, 0.5) AS q50, quantile_cont(l_quantity, 0.9) AS q90 FROM lineitem")
add("agg_two_level", lambda spark, d: rel.two_level_agg(read_table(spark, d, "documents", ["source", "n_chars"]), "source", "n_chars", 16), "SELECT source, sum(n_chars)::BIGINT AS total, count(*) AS n FROM documents GROUP BY 1")
add("agg_any_all_having", lambda spark, d: read_table(spark, d, "lineitem", ["l_orderkey", "l_returnflag", "l_quantity"]).groupBy("l_orderkey").agg(F.bool_or(F.col("l_returnflag") == "R").alias("some_r"), F.every(F.col("l_quantity") > 5).alias("all_big"), F.count(F.lit(1)).alias("n")).where("n > 5"), "SELECT l_orderkey, bool_or(l_returnflag = 'R') AS some_r, bool_and(l_quantity > 5) AS all_big, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 5")
add("agg_collect_small", lambda spark, d: read_table(spark, d, "nation", ["n_regionkey", "n_name"]).groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
add("window_ranks", lambda spark, d: (lambda w: read_table(spark, d, "supplier", ["s_suppkey", "s_nationkey", "s_acctbal"]).select("s_suppkey", F.row_number().over(w).alias("r"), F.ntile(3).over(w).alias("t"), F.lag("s_suppkey").over(w).alias("before"), F.round(F.cume_dist().over(w), 9).alias("c")))(W.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")), "SELECT s_suppkey, row_number() OVER w AS r, ntile(3) OVER w AS t, lag(s_suppkey) OVER w AS before, round(cume_dist() OVER w, 9) AS c FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)")
add("window_moving", lambda spark, d: (lambda w: read_table(spark, d, "events", ["event_id", "user_id", "value", "ts"]).select("event_id", F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 9).alias("a"), F.first("event_id").over(w.rowsBetween(-2, 0)).alias("f")))(W.partitionBy("user_id").orderBy("ts", "event_id")), "SELECT event_id, round(avg(value) OVER w, 9) AS a, first_value(event_id) OVER w AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)")
add("window_prefix_sum", lambda spark, d: rel.prefix_sum(read_table(spark, d, "part", ["p_partkey", "p_size"]), ["p_partkey"], "p_size", "upto"), "SELECT p_partkey, p_size, (sum(p_size) OVER (ORDER BY p_partkey))::BIGINT AS upto FROM part")
add("window_sessions", lambda spark, d: rel.sessionize(read_table(spark, d, "events", ["event_id", "user_id", "ts"]), ["user_id"], "ts", "event_id", 7200).select("event_id", F.col("session").cast("long").alias("session")), "SELECT event_id, (sum(n) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING))::BIGINT AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS n FROM events)")
add("topk_hubs", lambda spark, d: graphs.degrees(derive.order_part(spark, d)).orderBy(F.desc("d"), "vid").limit(20), f"WITH e AS ({EDGES['order_part']}) SELECT v AS vid, count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v ORDER BY d DESC, vid LIMIT 20")
add("topk_per_group", lambda spark, d: rel.top_k_per_group(read_table(spark, d, "orders", ["o_custkey", "o_orderkey", "o_totalprice"]), ["o_custkey"], [F.desc("o_totalprice"), "o_orderkey"], 2).select("o_custkey", "o_orderkey", "rank"), "SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rank FROM orders QUALIFY rank <= 2")
add("topk_offset", lambda spark, d: read_table(spark, d, "customer", ["c_custkey", "c_acctbal"]).orderBy(F.desc("c_acctbal"), "c_custkey").offset(10).limit(15), "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 15 OFFSET 10")
add("set_operations", lambda spark, d: (lambda a, b: a.intersect(b).select("k", F.lit("both").alias("side")).union(a.subtract(b).select("k", F.lit("first").alias("side"))))(read_table(spark, d, "documents", ["doc_id"]).select(F.col("doc_id").alias("k")), read_table(spark, d, "labels", ["doc_id"]).select(F.col("doc_id").alias("k"))), "SELECT k, side FROM (SELECT k, 'both' AS side FROM (SELECT doc_id AS k FROM documents INTERSECT SELECT doc_id FROM labels) UNION ALL SELECT k, 'first' FROM (SELECT doc_id AS k FROM documents EXCEPT SELECT doc_id FROM labels))")
add("set_all_and_dedupe", lambda spark, d: (lambda a: a.exceptAll(a.dropDuplicates()).groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("extra")))(read_table(spark, d, "lineitem", ["l_orderkey", "l_linenumber"])), "SELECT l_orderkey, sum(n - 1)::BIGINT AS extra FROM (SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY 1, 2) WHERE n > 1 GROUP BY 1")
add("scalar_text", lambda spark, d: read_table(spark, d, "pages", ["page_id", "url"]).select("page_id", F.lower(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).alias("host"), F.md5("url").alias("h"), F.length("url").cast("long").alias("n"), F.element_at(F.split("url", "/"), 4).alias("seg")), "SELECT page_id, lower(regexp_extract(url, '^[a-z]+://([^/]+)', 1)) AS host, md5(url) AS h, length(url) AS n, split_part(url, '/', 4) AS seg FROM pages")
add("scalar_json_time", lambda spark, d: read_table(spark, d, "events", ["event_id", "ts", "props"]).select("event_id", F.from_json("props", "k BIGINT")["k"].alias("k"), F.date_format("ts", "yyyy-MM-dd HH").alias("hour")), "SELECT event_id, (props->>'k')::BIGINT AS k, strftime(ts, '%Y-%m-%d %H') AS hour FROM events")
add("scalar_vector", lambda spark, d: (lambda e: e.alias("a").join(e.alias("b"), F.expr("b.vec_id = a.vec_id + 1")).select(F.col("a.vec_id").alias("vec_id"), F.round(cosine_distance(F.col("a.embedding"), F.col("b.embedding")), 4).alias("dist")))(read_table(spark, d, "embeddings", ["vec_id", "embedding"])), "SELECT a.vec_id, round(1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS dist FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
add("filter_families", lambda spark, d: read_table(spark, d, "part").where((F.col("p_size").between(5, 20)) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23") & ~F.col("p_type").like("%TIN%")).select("p_partkey"), "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') AND p_type NOT LIKE '%TIN%'")


def sql_views(spark: SparkSession, d: str) -> DataFrame:
    register_views(spark, d)
    return spark.sql("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")


add("source_sql_views", sql_views, "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
add("source_validate_edges", lambda spark, d: graphs.validate_edges(derive.doc_line(spark, d)), "SELECT 0 AS nulls, 0 AS loops, 0 AS disordered, 0 AS copies, 0 AS dangling")
add("profile_components", lambda spark, d: connectivity.component_sizes(connectivity.connected_components(derive.doc_line(spark, d)).labels).groupBy("size").agg(F.count(F.lit(1)).alias("components")), with_cc("doc_line", "SELECT size, count(*) AS components FROM (SELECT comp, count(*) AS size FROM c GROUP BY comp) GROUP BY size"))
add("profile_components_all_lines", lambda spark, d: connectivity.component_sizes(connectivity.connected_components(derive.doc_line_all(spark, d)).labels).groupBy("size").agg(F.count(F.lit(1)).alias("components")), with_cc("doc_line_all", "SELECT size, count(*) AS components FROM (SELECT comp, count(*) AS size FROM c GROUP BY comp) GROUP BY size"))


# streams

_DAY = "strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d')"
add("stream_tumbling", lambda spark, d: gs.drained(gs.windowed_degrees(gs.events_stream(spark, d)), "complete").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "user_id", "d"), f"SELECT {_DAY} AS day, user_id, count(*) AS d FROM events GROUP BY 1, 2")
add("stream_sketch", lambda spark, d: gs.drained(gs.windowed_sketch(gs.events_stream(spark, d)), "complete").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "x", "n"), f"SELECT {_DAY} AS day, bit_xor(event_id) AS x, count(*) AS n FROM events GROUP BY 1")
add("stream_dedupe", lambda spark, d: gs.drained(gs.dedupe_stream(gs.events_stream(spark, d)).select("event_id", "user_id")), "SELECT event_id, user_id FROM events")
add("stream_interval_join", lambda spark, d: gs.drained(gs.interval_stream_join(gs.events_stream(spark, d), "click", "purchase", 3600)), "SELECT a.event_id AS a_id, b.event_id AS b_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 3600 SECOND")
add("stream_user_runs", lambda spark, d: gs.drained(gs.user_runs(gs.events_stream(spark, d)), "update", ("user_id",)), "SELECT user_id, sum(n)::BIGINT AS runs, count(*) AS events FROM (SELECT user_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 1 HOUR THEN 0 ELSE 1 END AS n FROM events) GROUP BY 1")


def stream_components(spark: SparkSession, d: str) -> DataFrame:
    g = derive.geo_tree(spark, d)
    s = gs.stream_table(spark, d, "supplier").select(derive.typed(2, "s_suppkey").alias("src"), derive.typed(9, "s_nationkey").alias("dst"))
    keeper = gs.incremental(s)
    c = read_table(spark, d, "customer").select(derive.typed(1, "c_custkey").alias("src"), derive.typed(9, "c_nationkey").alias("dst"))
    keeper.absorb(c, 1)
    keeper.absorb(c, 1)  # a repeated batch changes nothing
    keeper.absorb(read_table(spark, d, "nation").select(derive.typed(9, "n_nationkey").alias("src"), derive.typed(10, "n_regionkey").alias("dst")), 2)
    return keeper.labels(g.vertices)


add("stream_components", stream_components, with_cc("geo_tree", "SELECT vid, comp FROM c"))


def stream_msf(spark: SparkSession, d: str) -> DataFrame:
    keeper = gs.IncrementalForest(spark, weighted=True)
    edges = derive.supplier_line(spark, d).edges
    for k in range(3):
        keeper.absorb(edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(3)) == k), k)
    return keeper.current().selectExpr(*_ROUND)


add("stream_msf", stream_msf, SQL["msf_supplier_line"])
