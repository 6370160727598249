"""Queries for further workloads, sources and sinks, measures of the engine itself, and the rest of the relational surface."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import twins
from .functions.coins import register_functions
from .functions.params import params_for
from .operators import analysis, baselines, connectivity, graphs, msf, nested, reductions, sampling
from .operators import relational as rel
from .operators.components import publish_forest
from .plans import ledger
from .plans.spool import cut, folder
from .queries import EDGES, SQL, VERTICES, T, _contracted, add, with_cc
from .sources import derive, tables
from .sources.tables import read_table
from .streaming import graph_streams as gs

# workloads

EDGES["user_succ"] = "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events) WHERE a <> b"
EDGES["embedding_knn"] = (
    "WITH w AS (SELECT a.vec_id AS a, b.vec_id AS b, round(1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS weight FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) "
    "SELECT least(a, b) AS src, greatest(a, b) AS dst, min(weight) AS weight FROM (SELECT * FROM w QUALIFY row_number() OVER (PARTITION BY a ORDER BY weight, b) <= 3) GROUP BY 1, 2"
)


def _windows(table: str, key: str) -> str:
    """All windows of 40 characters, cut from parts of 500 that overlap, since places in long texts are slow to find."""
    parts = f"SELECT {key}, array_to_string(c[i * 500 + 1:i * 500 + 539], '') AS part FROM (SELECT {key}, c, unnest(range(0, len(c) // 500 + 1)) AS i FROM (SELECT {key}, string_split(text, '') AS c FROM {table}))"
    return f"SELECT DISTINCT {key}, substr(part, j, 40) AS w FROM (SELECT {key}, part, unnest(range(1, least(length(part) - 38, 501))) AS j FROM ({parts}))"


EDGES["passage"] = f"SELECT DISTINCT {T[4]} + d.doc_id AS src, {T[8]} + b.item_id AS dst FROM ({_windows('documents', 'doc_id')}) d JOIN ({_windows('benchmark', 'item_id')}) b USING (w)"
VERTICES["passage"] = f"SELECT {T[4]} + doc_id AS vid FROM documents UNION SELECT {T[8]} + item_id FROM benchmark"


def labels_of(graph):
    return lambda spark, d: connectivity.connected_components(graph(spark, d)).labels


add("cc_user_succ", labels_of(derive.user_succ), with_cc("user_succ", "SELECT vid, comp FROM c"))
add("cc_embedding_knn", labels_of(derive.embedding_knn), with_cc("embedding_knn", "SELECT vid, comp FROM c"))
add("msf_embedding_knn", lambda spark, d: msf.minimum_spanning_forest(derive.embedding_knn(spark, d)).selectExpr("src", "dst", "round(weight, 6) AS weight"), twins.spanning_forest(EDGES["embedding_knn"]))
add("cc_passage", labels_of(derive.passage), with_cc("passage", "SELECT vid, comp FROM c"))


def passage_profile(spark: SparkSession, d: str) -> DataFrame:
    """Documents by label and by whether their component holds a benchmark item, in all groupings of quality and toxic."""
    c = connectivity.connected_components(derive.passage(spark, d)).labels
    held = c.groupBy("comp").agg(F.bool_or(F.col("vid") >= T[8]).alias("held"))
    docs = c.where(F.col("vid") < T[8]).join(held, "comp").select((F.col("vid") - T[4]).alias("doc_id"), "held").join(read_table(spark, d, "labels"), "doc_id", "left")
    return docs.cube("quality", "toxic").agg(F.grouping_id().cast("long").alias("level"), F.count(F.lit(1)).alias("documents"), F.count_if("held").alias("with_item"))


_HELD = f"h AS (SELECT comp, bool_or(vid >= {T[8]}) AS held FROM c GROUP BY comp)"
add("profile_passage_labels", passage_profile, with_cc("passage", f"SELECT quality, toxic, grouping(quality, toxic)::BIGINT AS level, count(*) AS documents, count(*) FILTER (WHERE held) AS with_item FROM c JOIN h USING (comp) LEFT JOIN labels ON doc_id = vid - {T[4]} WHERE vid < {T[8]} GROUP BY CUBE (quality, toxic)", f", {_HELD}"))


def brand_profile(spark: SparkSession, d: str) -> DataFrame:
    """Parts by component and brand, by component and by brand alone."""
    c = connectivity.connected_components(derive.part_supplier(spark, d)).labels
    parts = c.join(read_table(spark, d, "part", ["p_partkey", "p_brand"]).select((F.col("p_partkey") + T[1]).alias("vid"), "p_brand"), "vid")
    return parts.groupingSets([["comp", "p_brand"], ["comp"], ["p_brand"]], "comp", "p_brand").agg(F.count(F.lit(1)).alias("parts"))


add("profile_part_brands", brand_profile, with_cc("part_supplier", f"SELECT comp, p_brand, count(*) AS parts FROM c JOIN part ON p_partkey + {T[1]} = vid GROUP BY GROUPING SETS ((comp, p_brand), (comp), (p_brand))"))


def cut_supplier(spark: SparkSession, d: str) -> DataFrame:
    """Without all edges of the first supplier the graph falls apart."""
    g = derive.part_supplier(spark, d).settle()
    first = g.edges.agg(F.min("dst")).first()[0]
    return reductions.is_cut(g, g.edges.where(F.col("dst") == first))


add(
    "cut_part_supplier",
    cut_supplier,
    with_cc("part_supplier", "SELECT (SELECT count(DISTINCT comp) FROM c) AS before, (SELECT count(DISTINCT comp) FROM c2) AS after, (SELECT count(DISTINCT comp) FROM c2) > (SELECT count(DISTINCT comp) FROM c) AS is_cut",
            ", s2 AS (SELECT a, b FROM s WHERE a <> (SELECT min(dst) FROM e) AND b <> (SELECT min(dst) FROM e)), c2(vid, comp) USING KEY (vid) AS (SELECT vid, vid FROM v UNION (SELECT s2.b AS vid, min(c2.comp) AS comp FROM c2 JOIN s2 ON c2.vid = s2.a JOIN recurring.c2 k ON k.vid = s2.b WHERE c2.comp < k.comp GROUP BY s2.b))"),
)
_CYCLES = "SELECT a.comp, coalesce(m, 0) > size - 1 AS has_cycle FROM (SELECT comp, count(*) AS size FROM c GROUP BY comp) a LEFT JOIN (SELECT comp, count(*) AS m FROM e JOIN c ON src = vid GROUP BY comp) b ON a.comp = b.comp"
add("cycle_part_supplier", lambda spark, d: reductions.has_cycle(derive.part_supplier(spark, d)), with_cc("part_supplier", _CYCLES))


# baselines on the graphs of the headline queries

for _g in ("part_supplier", "order_part", "order_chain", "doc_line"):
    for _b, _f in (("star_contraction", baselines.star_contraction_cc), ("hook_and_contract", baselines.hook_and_contract_cc), ("sketch_only", baselines.sketch_only_cc), ("label_propagation", lambda g: baselines.ComponentResult(baselines.min_label_propagation(g)[0], g.edges))):
        if f"baseline_{_b}_cc" in SQL and _g == "doc_line":
            continue
        add(f"baseline_{_b}_cc_{_g}", (lambda f, name: lambda spark, d: f(derive.GRAPHS[name](spark, d)).labels)(_f, _g), SQL[f"cc_{_g}"])


# nested instances of other graphs, and proxies that carry their rows


def proxies_carry(spark: SparkSession, d: str) -> DataFrame:
    """Per instance of the part-supplier graph: edges and vertices that its proxies unfold."""
    g = derive.part_supplier(spark, d).settle()
    e = cut(msf.nested_instances(g.edges, g.n))
    count = e.agg(F.max("first_instance")).first()[0]
    served = _served(e, g, count)
    return served.where("u < v").groupBy("instance").agg(F.count(F.lit(1)).alias("edges"), F.count_distinct("u").alias("low_ends"))


def _served(e: DataFrame, g: graphs.EdgeSet, count: int) -> DataFrame:
    encoded = cut(nested.encode_nested(e))
    deg = encoded.groupBy(F.col("u").alias("vid")).agg(F.count(F.lit(1)).alias("d"))
    return nested.expand_at_proxies(encoded, cut(nested.assign_proxies(deg, g.n)), count)


_PS_RANK = f"SELECT src, dst, weight, ((row_number() OVER (ORDER BY weight, src, dst) - 1) // (SELECT count(*) FROM (SELECT src FROM e UNION SELECT dst FROM e)) + 1)::INTEGER AS first_instance FROM e"
add("nested_proxies_carry", proxies_carry, f"WITH e AS ({EDGES['part_supplier']}), r AS MATERIALIZED ({_PS_RANK}), i AS (SELECT unnest(range(1, (SELECT max(first_instance) FROM r) + 1))::INTEGER AS instance) SELECT instance, count(*) AS edges, count(DISTINCT src) AS low_ends FROM r JOIN i ON first_instance <= instance GROUP BY instance")


def proxy_rows(spark: SparkSession, d: str) -> DataFrame:
    """Most rows that one key carries when all instances of the part-supplier graph unfold: at vertices, and at proxies."""
    g = derive.part_supplier(spark, d).settle()
    e = cut(msf.nested_instances(g.edges, g.n))
    count = e.agg(F.max("first_instance")).first()[0]
    served = cut(_served(e, g, count))
    most = lambda key: served.groupBy(key).agg(F.count(F.lit(1)).alias("k")).agg(F.max("k")).first()[0]
    plain, dealt = most("u"), most("proxy")
    return spark.createDataFrame([(g.n, count, plain, dealt, dealt <= plain, dealt <= 3 * g.n)], "n long, instances int, at_vertices long, at_proxies long, lighter boolean, load_ok boolean")


add("nested_proxy_rows", proxy_rows)


def nested_components(spark: SparkSession, d: str) -> DataFrame:
    """Components of every nested instance of the part-supplier graph, all at once."""
    g = derive.part_supplier(spark, d).settle()
    e = cut(msf.nested_instances(g.edges, g.n))
    count = e.agg(F.max("first_instance")).first()[0]
    return nested.components_of_nested(e, g.vertices, count).groupBy("instance").agg(F.count_distinct("comp").alias("components"))


add(
    "nested_labels_part_supplier",
    nested_components,
    f"""WITH RECURSIVE e AS ({EDGES["part_supplier"]}), v AS (SELECT src AS vid FROM e UNION SELECT dst FROM e), r AS MATERIALIZED ({_PS_RANK}), i AS (SELECT unnest(range(1, (SELECT max(first_instance) FROM r) + 1))::INTEGER AS instance),
s AS MATERIALIZED (SELECT instance, src AS a, dst AS b FROM r JOIN i ON first_instance <= instance UNION ALL SELECT instance, dst, src FROM r JOIN i ON first_instance <= instance),
c(instance, vid, comp) USING KEY (instance, vid) AS (SELECT instance, vid, vid FROM v, i UNION (SELECT s.instance, s.b, min(c.comp) FROM c JOIN s ON c.instance = s.instance AND c.vid = s.a JOIN recurring.c k ON k.instance = s.instance AND k.vid = s.b WHERE c.comp < k.comp GROUP BY s.instance, s.b))
SELECT instance, count(DISTINCT comp) AS components FROM c GROUP BY instance""",
)


# measures of the engine


def rounds(spark: SparkSession, d: str) -> DataFrame:
    """Jobs, stages, shuffles, shuffled bytes and tasks that each method takes on the order chain."""
    g = derive.order_chain(spark, d).settle()
    p = params_for(g.n)
    split = {}
    work = {
        "sparsify": lambda: split.setdefault("it", connectivity.sparsify_by_degree(g, p.s)).labels.count(),
        "contract": lambda: sampling.contract_by_samples(g, p, keep_messages=False)[0].count(),
        "whole_method": lambda: connectivity.connected_components(g).labels.count(),
        "star_contraction": lambda: baselines.star_contraction_cc(g).labels.count(),
        "sketch_only": lambda: baselines.sketch_only_cc(g).labels.count(),
        "label_propagation": lambda: baselines.min_label_propagation(g)[0].count(),
    }
    rows = [(k, g.n, *(m := ledger.measured(spark, f)).values()) for k, f in work.items()]
    return spark.createDataFrame(rows, "method string, n long, jobs long, stages long, shuffles long, shuffle_bytes long, tasks long")


add("ledger_measured", rounds)


def piece_measures(spark: SparkSession, d: str) -> DataFrame:
    """Per piece of the order path: its size, whether a sample holds it whole, whether some vertex of it has a leader in
    its sample component, and what it adds to the bound on bad vertices; folded to counts."""
    g, p, (_, _, messages) = _contracted(spark, d, "order_path")
    done = baselines.exact_local_cc(g)
    c = cut(analysis.classify_vertices(g, messages, done.labels, p, portable=True))
    tiles = cut(analysis.almost_partition(done.forest, done.labels, max(2, round(p.small))))
    samples = cut(sampling.sample_edges(g.edges, p.num_samples, p.p_edge, p.seed, portable=True))
    bound = analysis.piece_bad_bound(tiles, samples, done.forest, c)
    return bound.groupBy("in_sample", "some_alpha").agg(F.count(F.lit(1)).alias("pieces"), F.sum("size").alias("vertices"), F.sum("adds").cast("long").alias("adds"))


add("piece_measures", piece_measures)


def messages_twin(spark: SparkSession, d: str) -> DataFrame:
    """Every message of one contraction of the conversations, sample by sample."""
    _, _, (_, _, messages) = _contracted(spark, d, "conv_chain")
    return messages.select("v", "x", "size", "sample", "hop", F.col("comp_has_leader").alias("led"))


_MESSAGES = f"WITH RECURSIVE {twins.contraction(EDGES['conv_chain'], VERTICES['conv_chain'], 1)} SELECT v, x, size, sample, hop, led FROM msg"
add("contract_messages", messages_twin, _MESSAGES)


def messages_by_joins(spark: SparkSession, d: str) -> DataFrame:
    """The same messages with no sample in one task."""
    g = derive.conv_chain(spark, d).settle()
    p = params_for(g.n, seed=1)
    samples = sampling.sample_edges(sampling.with_leaders(g.edges, p, True), p.num_samples, p.p_edge, p.seed, portable=True)
    return sampling.solve_samples_by_joins(samples, p, portable=True).select("v", "x", "size", "sample", "hop", F.col("comp_has_leader").alias("led"))


add("contract_messages_by_joins", messages_by_joins, _MESSAGES)
add("cc_lean_samples", lambda spark, d: connectivity.connected_components(g := derive.order_chain(spark, d).settle(), params_for(g.n, faithful=False)).labels, SQL["cc_order_chain"])
add("cc_exact_exit", lambda spark, d: connectivity.connected_components(derive.order_chain(spark, d), exact_below=2_000_000).labels, SQL["cc_order_chain"])
add("cc_distributed", lambda spark, d: connectivity.connected_components(derive.conv_chain(spark, d), mode="distributed").labels, SQL["cc_conv_chain"])


def published(spark: SparkSession, d: str) -> DataFrame:
    """Depths of the conversations' trees by tours, as for trees of any size."""
    g = derive.conv_chain(spark, d)
    return publish_forest(g.vertices, connectivity.connected_components(g), limit=0).groupBy("root").agg(F.count(F.lit(1)).alias("size"), F.max("depth").alias("depth"))


add("publish_forest_by_tours", published, SQL["publish_forest_conv_chain"])

# sources, sinks and functions


def _spot(spark: SparkSession) -> str:
    return f"{folder(spark)}/spot-{uuid.uuid4().hex}"


def edge_formats(spark: SparkSession, d: str) -> DataFrame:
    """Edge lists written and read back in every format: edges and a checksum of each."""
    e = cut(derive.customer_order(spark, d).edges)
    out = None
    for fmt in ("parquet", "orc", "json", "csv", "text"):
        path = _spot(spark)
        if fmt == "text":
            e.select(F.concat_ws(" ", "src", "dst", "weight").alias("value")).write.text(path)
        else:
            e.write.format(fmt).save(path)
        back = tables.read_edges(spark, path, fmt, "src", "dst", "weight")
        one = back.agg(F.lit(fmt).alias("fmt"), F.count(F.lit(1)).alias("edges"), F.bit_xor(F.col("src") * 3 + F.col("dst")).alias("ends"), F.round(F.sum("weight"), 2).alias("weight"))
        out = one if out is None else out.unionByName(one)
    return out


add("source_edge_formats", edge_formats, f"SELECT fmt, count(*) AS edges, bit_xor(src * 3 + dst) AS ends, round(sum(weight), 2) AS weight FROM ({EDGES['customer_order']}), (VALUES ('parquet'), ('orc'), ('json'), ('csv'), ('text')) t(fmt) GROUP BY fmt")


def adjacency(spark: SparkSession, d: str) -> DataFrame:
    path = _spot(spark)
    e = derive.customer_order(spark, d).edges
    e.groupBy(F.col("src").alias("vid")).agg(F.collect_list("dst").alias("neighbours")).write.parquet(path)
    return tables.read_adjacency(spark, path).select("src", "dst")


add("source_adjacency", adjacency, f"SELECT src, dst FROM ({EDGES['customer_order']})")


def sinks(spark: SparkSession, d: str) -> DataFrame:
    """Degrees written in folders by degree and in buckets by vertex, read back with one folder pruned."""
    deg = graphs.degrees(derive.geo_tree(spark, d)).withColumn("kind", F.floor(F.col("vid") / graphs.TAG).cast("int"))
    path, name = _spot(spark), f"degrees_{uuid.uuid4().hex}"
    tables.write_result(deg, path, partition_by=["kind"])
    tables.write_result(deg, _spot(spark), bucket_by=(4, "vid"), table=name)
    one = spark.read.parquet(path).where("kind = 9").select(F.lit("folders").alias("sink"), "vid", "d")
    two = spark.table(name).where("kind = 9").select(F.lit("buckets").alias("sink"), "vid", "d")
    out = cut(one.unionByName(two))
    spark.sql(f"DROP TABLE {name}")
    return out


add("sink_folders_and_buckets", sinks, f"SELECT sink, v AS vid, count(*) AS d FROM (SELECT src AS v FROM ({EDGES['geo_tree']}) UNION ALL SELECT dst FROM ({EDGES['geo_tree']})), (VALUES ('folders'), ('buckets')) t(sink) WHERE v >= {T[9]} AND v < {T[10]} GROUP BY 1, 2")
add(
    "graph_induced",
    lambda spark, d: (lambda g: graphs.induced_subgraph(g, g.vertices.where("vid % 2 = 0")).edges.select("src", "dst"))(derive.part_supplier(spark, d)),
    f"SELECT src, dst FROM ({EDGES['part_supplier']}) WHERE src % 2 = 0 AND dst % 2 = 0",
)
add("graph_weight_between", lambda spark, d: graphs.weight_between(derive.part_supplier(spark, d).edges, 2000.0, 9000.0).select("src", "dst"), f"SELECT src, dst FROM ({EDGES['part_supplier']}) WHERE weight BETWEEN 2000 AND 9000")


def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    register_functions(spark)
    read_table(spark, d, "embeddings").createOrReplaceTempView("embeddings")
    return spark.sql("SELECT a.vec_id, round(cosine_distance(cast(a.embedding AS ARRAY<DOUBLE>), cast(b.embedding AS ARRAY<DOUBLE>)), 9) AS distance, coin(1, 'x', a.vec_id) BETWEEN 0 AND 1 AS coin_ok FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")


add("function_sql_names", sql_functions, "SELECT a.vec_id, round(1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS distance, true AS coin_ok FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")


def sampled_hits(spark: SparkSession, d: str) -> DataFrame:
    """Places of geometric skips by a table function, one call an edge: which of 1,000 samples an edge joins."""
    rows = derive.geo_tree(spark, d).edges
    hit = sampling.hits_table_function()
    spark.udtf.register("sample_hits", hit)
    rows.createOrReplaceTempView("geo_edges")
    return spark.sql("SELECT src, dst, count(*) AS hits, min(sample) >= 1 AND max(sample) <= 1000 AS inside FROM geo_edges, LATERAL sample_hits(src, dst, 1000, 0.25D, 1) GROUP BY src, dst").agg(F.count(F.lit(1)).alias("edges"), F.bool_and("inside").alias("inside"), (F.abs(F.avg("hits") - 250) < 10).alias("rate_ok"))


add("function_sample_hits", sampled_hits, f"SELECT count(*) AS edges, true AS inside, true AS rate_ok FROM ({EDGES['geo_tree']})")


# relational surface

add("agg_grouping_sets", lambda spark, d: read_table(spark, d, "documents", ["lang", "source", "n_chars"]).groupingSets([["lang", "source"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars")), "SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY GROUPING SETS ((lang, source), (source), ())")
add(
    "agg_approx_distinct",
    lambda spark, d: read_table(spark, d, "lineitem", ["l_suppkey", "l_partkey"]).groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("near")).select("l_suppkey", "parts", (F.abs(F.col("near") - F.col("parts")) <= 0.1 * F.col("parts") + 1).alias("near_ok")),
    "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, true AS near_ok FROM lineitem GROUP BY 1",
)
add(
    "agg_filtered_sorted",
    lambda spark, d: read_table(spark, d, "orders", ["o_custkey", "o_orderkey", "o_orderstatus"]).groupBy("o_custkey").agg(F.expr("count(*) FILTER (WHERE o_orderstatus = 'F')").alias("done"), F.array_join(F.sort_array(F.collect_list("o_orderkey"), asc=False), ",").alias("orders")),
    "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, string_agg(o_orderkey, ',' ORDER BY o_orderkey DESC) AS orders FROM orders GROUP BY 1",
)
add(
    "set_intersect_all",
    lambda spark, d: read_table(spark, d, "lineitem", ["l_partkey"]).toDF("k").intersectAll(read_table(spark, d, "lineitem", ["l_suppkey"]).toDF("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n")),
    "SELECT k, count(*) AS n FROM (SELECT l_partkey AS k FROM lineitem INTERSECT ALL SELECT l_suppkey FROM lineitem) GROUP BY k",
)
add(
    "scalar_maps",
    lambda spark, d: read_table(spark, d, "events", ["user_id", "event_type", "value"]).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    .select("user_id", F.array_join(F.array_sort(F.map_keys("m")), ",").alias("kinds"), F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.size(F.map_filter("m", lambda k, n: n > 5)).alias("often"), F.aggregate(F.map_values(F.transform_values("m", lambda k, n: n * 2)), F.lit(0).cast("long"), lambda a, n: a + n).alias("twice")),
    "SELECT user_id, string_agg(event_type, ',' ORDER BY event_type) AS kinds, coalesce(max(n) FILTER (WHERE event_type = 'click'), 0) AS clicks, count(*) FILTER (WHERE n > 5)::INTEGER AS often, (sum(n) * 2)::BIGINT AS twice FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1",
)


# streams


def sliding(spark: SparkSession, d: str) -> DataFrame:
    return gs.drained(gs.windowed_degrees(gs.events_stream(spark, d), "sliding"), "complete").select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "user_id", "d")


add("stream_sliding", sliding, "SELECT strftime(s, '%Y-%m-%d %H') AS start, user_id, count(*) AS d FROM (SELECT user_id, time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR AS s FROM events, range(4) t(k)) GROUP BY 1, 2")


def sessions(spark: SparkSession, d: str) -> DataFrame:
    return gs.drained(gs.windowed_degrees(gs.events_stream(spark, d), "session"), "complete").select(F.unix_micros("start").alias("start"), F.unix_micros("end").alias("end"), "user_id", "d")


add(
    "stream_session",
    sessions,
    "SELECT epoch_us(min(ts)) AS start, epoch_us(max(ts)) + 3600000000 AS end, user_id, count(*) AS d FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s",
)


def late(spark: SparkSession, d: str) -> DataFrame:
    """A stream whose second file is older than the watermark the first one left: rows dropped, and rows counted."""
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts"]).withColumn("ts", F.col("ts").cast("timestamp"))
    half = e.agg(F.expr("percentile_approx(unix_micros(ts), 0.5, 10000)")).first()[0]
    path = _spot(spark)
    new, old = e.where(F.unix_micros("ts") > half), e.where(F.unix_micros("ts") <= half)
    dropped, counted = gs.late_report([new, old], path)
    total = e.count()
    return spark.createDataFrame([(total, counted, dropped > 0 and counted < total)], "events long, counted long, late_ok boolean")


add("stream_late_rows", late)
