"""The proofs' statements as tests on planted and derived graphs."""

import math
import random

import pytest
from pyspark.sql import functions as F

from fewrounds.functions.params import params_for
from fewrounds.operators import analysis, baselines, connectivity, graphs, msf, nested, reductions, sampling, sketches, sparsify
from fewrounds.operators.components import complete_partition, as_links, pointer_double, publish_forest
from fewrounds.operators.graphs import EdgeSet, build, generate_graph


def truth(g):
    up = {r["vid"]: r["vid"] for r in g.vertices.collect()}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for r in g.edges.collect():
        a, b = find(r["src"]), find(r["dst"])
        up[max(a, b)] = min(a, b)
    return {v: find(v) for v in up}


def found(labels):
    return {r["vid"]: r["comp"] for r in labels.collect()}


def random_graph(spark, n, m, seed, weight=False):
    r = random.Random(seed)
    rows = [(r.randrange(n), r.randrange(n), float(r.randint(1, 5))) for _ in range(m)]
    e = spark.createDataFrame(rows or [], "src long, dst long, weight double")
    return build(e, spark.range(n).select(F.col("id").alias("vid")), "weight" if weight else None)


@pytest.mark.parametrize("kind", ["path", "cycle", "star", "complete", "grid", "tree", "sparse"])
def test_components_of_planted_graphs(spark, kind):
    g = generate_graph(spark, kind, 30, 1)
    assert found(connectivity.connected_components(g).labels) == truth(g)


def test_components_with_sketches_only(spark):
    g = random_graph(spark, 60, 45, 3)
    p = params_for(60, seed=4)
    done = connectivity.connected_components(g, p, exact_below=0)
    assert found(done.labels) == truth(g)
    check = analysis.forest_checks(g, done).first()
    assert check["size_ok"] and check["inside_ok"] and check["spans_ok"]


def test_empty_single_and_dirty_input(spark):
    none = build(spark.createDataFrame([], "src long, dst long"), spark.range(0).select(F.col("id").alias("vid")))
    assert connectivity.connected_components(none).labels.count() == 0
    one = build(spark.createDataFrame([], "src long, dst long"), spark.range(3).select(F.col("id").alias("vid")))
    assert found(connectivity.connected_components(one).labels) == {0: 0, 1: 1, 2: 2}
    dirty = build(spark.createDataFrame([(1, 1), (1, 2), (2, 1), (None, 3), (5, 4)], "src long, dst long"))
    assert sorted((r.src, r.dst) for r in dirty.edges.collect()) == [(1, 2), (4, 5)]
    assert found(connectivity.connected_components(dirty).labels) == {1: 1, 2: 1, 4: 4, 5: 4}


@pytest.mark.parametrize("seed", range(3))
def test_sparsify_guarantees(spark, seed):
    g = random_graph(spark, 40, 20 + 25 * seed, seed)
    for s in (1, 2, 4):
        split = sparsify.sparsify_by_degree(g, s)
        m = analysis.split_measures(g, split, s).first()
        assert m["size_ok"] and m["degree_ok"] and (m["count_ok"] or s == 1)
        assert m["edges_a"] + m["edges_b"] == g.edges.count()
    hooks = split.hooks1
    unordered = hooks.select(F.least("v", "u").alias("src"), F.greatest("v", "u").alias("dst")).distinct()
    _, tree = complete_partition(as_links(unordered), "task")
    assert tree.count() == unordered.count()  # the hooks form a forest


def test_distributed_equals_task(spark):
    g = random_graph(spark, 50, 60, 9, True)
    for weighted in (False, True):
        links = as_links(g.edges if weighted else g.edges.select("src", "dst"))
        a, fa = complete_partition(links, "task", weighted=weighted)
        b, fb = complete_partition(links, "distributed", weighted=weighted)
        group = lambda d: {frozenset(v for v in d if d[v] == c) for c in set(d.values())}
        assert group(found(a)) == group(found(b)) and fa.count() == fb.count()
        if weighted:
            assert set(map(tuple, fa.collect())) == set(map(tuple, fb.collect()))
    chain = spark.range(40).select(F.col("id").alias("vid"), F.greatest(F.col("id") - 1, F.lit(0)).alias("parent"))
    assert {r["root"] for r in pointer_double(chain, 0).collect()} == {0} == {r["root"] for r in pointer_double(chain).collect()}


def test_sampling_rates_and_forest(spark):
    g = generate_graph(spark, "path", 400)
    for portable in (False, True):
        n = sampling.sample_edges(g.edges, 20, 0.3, 5, portable).count()
        assert abs(n - 399 * 20 * 0.3) < 5 * math.sqrt(399 * 20 * 0.3)
    p = params_for(400, seed=2)
    labels, forest, messages = sampling.contract_by_samples(g, p)
    assert forest.join(g.edges, ["src", "dst"], "left_anti").isEmpty()
    _, tree = complete_partition(as_links(forest), "task")
    assert tree.count() == forest.count() == 400 - labels.select("comp").distinct().count()
    classes = analysis.classify_vertices(g, messages, labels, p)
    assert classes.where("class = 'alpha' AND NOT has_leader").isEmpty() and classes.where("bad AND class <> 'gamma'").isEmpty()


def test_sketch_recovers_single_edges(spark):
    g = build(spark.createDataFrame([(1, 2), (3, 4)], "src long, dst long"))
    labels = g.vertices.select("vid", F.col("vid").alias("comp"))
    got = sketches.recovered(sketches.component_sketch(g.edges, labels, 1), 0)
    assert {(r.comp, r.src, r.dst) for r in got.collect()} == {(1, 1, 2), (2, 1, 2), (3, 3, 4), (4, 3, 4)}


@pytest.mark.parametrize("seed", range(2))
def test_forests_equal_kruskal(spark, seed):
    g = random_graph(spark, 25, 120, seed, True)
    exact = set(map(tuple, msf.exact_local_msf(g).collect()))
    for method in (lambda: msf.minimum_spanning_forest(g, force_filter=True, seed=seed), lambda: msf.hook_and_contract_msf(g), lambda: msf.squared_growth_msf(g)[0], lambda: msf.with_weights(msf.bucketed_forest(g, "uniform"), g.edges)):
        assert set(map(tuple, method().select("src", "dst", "weight").collect())) == exact


@pytest.mark.parametrize("seed", range(2))
def test_light_edges_by_joins_equal_lifting(spark, seed):
    g = random_graph(spark, 30, 150, seed, True)
    thin = EdgeSet(g.vertices, msf.thin_by_sampling(g, 0.2, seed))
    forest = msf.exact_local_msf(thin)
    rows = lambda df: set(map(tuple, df.select("src", "dst", "weight").collect()))
    one, two = msf.light_edges(g, forest), msf.light_edges(g, forest, limit=0)
    assert two.count() == len(rows(two)) < g.edges.count()
    assert rows(one) == rows(two) >= rows(msf.exact_local_msf(g))
    assert rows(msf.light_edges(g, forest.where("false"), limit=0)) == rows(g.edges)


def test_baselines_agree(spark):
    g = random_graph(spark, 40, 30, 11)
    want = truth(g)
    for f in (baselines.star_contraction_cc, baselines.hook_and_contract_cc, baselines.exact_local_cc, baselines.sketch_only_cc, baselines.growth_then_sketch_cc):
        assert found(f(g).labels) == want, f.__name__
    assert found(baselines.min_label_propagation(g)[0]) == want


def test_almost_partition(spark):
    for kind, s in (("path", 3), ("star", 4), ("tree", 3)):
        g = generate_graph(spark, kind, 70, 5)
        done = baselines.exact_local_cc(g)
        rows = analysis.almost_partition(done.forest, done.labels, s).collect()
        sizes, shared = {}, {}
        for r in rows:
            sizes[r.piece] = sizes.get(r.piece, 0) + 1
            shared[r.piece] = shared.get(r.piece, 0) + (not r.is_unique)
        assert {r.vid for r in rows} == set(range(70)) and all(s <= x <= 3 * s for x in sizes.values()) and max(shared.values()) <= 1


def test_reductions(spark):
    assert reductions.is_bipartite(generate_graph(spark, "cycle", 6)) and not reductions.is_bipartite(generate_graph(spark, "cycle", 5))
    path = generate_graph(spark, "path", 5)
    assert reductions.is_cut(path, path.edges.where("src = 2")).first()["is_cut"]
    assert not reductions.edge_on_cycle(path, 1, 2) and reductions.edge_on_cycle(generate_graph(spark, "cycle", 5), 0, 1)
    assert [r["has_cycle"] for r in reductions.has_cycle(path).collect()] == [False]


def test_nested(spark):
    g = random_graph(spark, 12, 60, 2, True)
    e = msf.nested_instances(g.edges, 12)
    k = e.agg(F.max("first_instance")).first()[0]
    one, two = (nested.components_of_nested(e, g.vertices, k, m) for m in ("incremental", "parallel"))
    group = lambda df: {frozenset((r.instance, r.vid) for r in rows) for rows in _by(df)}
    assert group(one) == group(two)
    assert set(map(tuple, nested.bucket_kruskal(e, one).collect())) == {(r.src, r.dst) for r in msf.exact_local_msf(g).collect()}
    assert nested.decode(nested.encode_nested(e), 2).exceptAll(e.where("first_instance <= 2").select("src", "dst")).isEmpty()


def _by(df):
    rows = {}
    for r in df.collect():
        rows.setdefault((r.instance, r.comp), []).append(r)
    return rows.values()


def test_published_trees(spark):
    g = generate_graph(spark, "grid", 36)
    done = connectivity.connected_components(g)
    for limit in (1000, 1):
        p = {r.vid: r.parent for r in publish_forest(g.vertices, done, limit).collect()}
        assert len(p) == 36 and p[0] == 0
        assert all((min(a, b), max(a, b)) in {(r.src, r.dst) for r in done.forest.collect()} for a, b in p.items() if a != b)


def test_answers_do_not_depend_on_coins(spark):
    g = random_graph(spark, 80, 50, 21)
    assert len({tuple(sorted(found(connectivity.connected_components(g, params_for(80, seed=s), exact_below=0).labels).items())) for s in (1, 2)}) == 1


def test_lines_that_many_documents_share(spark, tmp_path):
    """25 documents tied by one line only, more than doc_line takes, are one component."""
    from fewrounds.queries import QUERIES

    line = "one and the same line of more than forty characters"
    spark.createDataFrame([(i, f"{line}\nown {i}" if i < 25 else f"own {i}") for i in range(27)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    labels = QUERIES["cc_doc_line_all"](spark, str(tmp_path)).collect()
    assert len(labels) == 28 and len({r["comp"] for r in labels}) == 3


def test_nested_queries_cover_all_instances(spark, tmp_path):
    """20 suppliers make 10 instances; every one is labelled, sparsified and decoded."""
    from fewrounds.queries import QUERIES

    balance = [float((7 * i * i + 3 * i) % 101) for i in range(20)]
    spark.createDataFrame(list(enumerate(balance)), "s_suppkey long, s_acctbal double").write.parquet(str(tmp_path / "supplier.parquet"))
    ranked = sorted((abs(balance[a] - balance[b]), a, b) for a in range(20) for b in range(a + 1, 20))
    want, edges = [], []
    for i in range(1, 11):
        up = list(range(20))
        for _, a, b in ranked[: 20 * i]:
            edges.append((i, a, b))
            up = [up[b] if x == up[a] else x for x in up]
        want.append((i, len(set(up)), max(up.count(x) for x in up), True))
    run = lambda name: sorted(map(tuple, QUERIES[name](spark, str(tmp_path)).collect()))
    assert run("nested_labels_all") == want
    assert run("nested_encoding_all") == sorted(edges)
    assert run("nested_sparsify_all") == [(True, True, True, len(edges))]
