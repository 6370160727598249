"""Parts of the method that have two forms agree, and loops end with what plain versions give."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from fewrounds.functions.params import params_for
from fewrounds.operators import graphs, msf, nested, sampling, sketches
from fewrounds.operators.components import ComponentResult, as_links, complete_partition, publish_forest, root_by_tours
from fewrounds.operators.connectivity import connected_components
from fewrounds.plans import spool


def sparse(spark, n, m, seed):
    r = random.Random(seed)
    edges = {tuple(sorted(r.sample(range(n), 2))) for _ in range(m)}
    return graphs.build(spark.createDataFrame([(a, b, float(r.randrange(50))) for a, b in edges], "src long, dst long, weight double"), spark.range(n).withColumnRenamed("id", "vid"), "weight").settle(), edges


def rows(df):
    return sorted(map(str, df.collect()))


def test_hash_equals_the_sql_function(spark):
    r = np.random.default_rng(1)
    a, b = (r.integers(-(1 << 62), 1 << 62, 200) for _ in range(2))
    df = spark.createDataFrame([(int(x), int(y)) for x, y in zip(a, b, strict=True)], "a long, b long")
    want = [x.h for x in df.select(F.xxhash64(F.lit(7).cast("long"), F.lit(3).cast("long"), "a", "b").alias("h")).collect()]
    assert sketches.xxhash_of_longs(7, 3, a, b).tolist() == want


@pytest.mark.parametrize("seed", [1, 2])
def test_messages_in_three_ways(spark, seed):
    g, _ = sparse(spark, 60, 80, seed)
    p = params_for(60, seed=seed, num_samples=9)
    for portable in (False, True):
        samples = spool.cut(sampling.sample_edges(g.edges, 9, 0.5, seed, portable))
        one = spool.cut(sampling.solve_sample(samples, p, portable))
        assert rows(one) == rows(sampling.solve_samples_by_joins(samples, p, portable).select(*one.columns))
        assert rows(sampling.best_message(one)) == rows(sampling.best_message(sampling.best_of_samples(samples, p, portable)))
    again = sampling.sample_edges(g.edges.repartition(5), 9, 0.5, seed)
    assert rows(again) == rows(sampling.sample_edges(g.edges, 9, 0.5, seed))


def test_sketches_in_task_and_by_joins(spark):
    g, edges = sparse(spark, 120, 110, 3)
    alone = g.vertices.select("vid", F.col("vid").alias("comp"))
    nothing = g.edges.select("src", "dst").where("false")
    exact, _ = complete_partition(as_links(g.edges.select("src", "dst")), "task")
    parts = lambda labels: len({r.comp for r in labels.collect()})
    want = parts(exact) + 120 - exact.count()
    for options in ({}, {"reps": 1}, {"mode": "distributed"}, {"task_limit": 0, "reps": 2}):
        log: list = []
        done = sketches.finish_by_sketches(g, alone, nothing, log=log, **options)
        forest = {(r.src, r.dst) for r in done.forest.collect()}
        assert parts(done.labels) == want and len(forest) == 120 - want and forest <= edges and log


def test_tours_root_trees_of_any_shape(spark):
    r = random.Random(5)
    edges = [(r.randrange(k) if k % 3 else k - 1, k) for k in range(1, 40)] + [(100, 101), (101, 102), (200, 201)]
    vertices = spark.createDataFrame([(v,) for v in sorted({x for e in edges for x in e} | {300})], "vid long")
    comp = lambda v: 0 if v < 100 else 100 if v < 200 else 200 if v < 300 else 300
    labels = spark.createDataFrame([(row.vid, comp(row.vid)) for row in vertices.collect()], "vid long, comp long")
    result = ComponentResult(labels, spark.createDataFrame(edges, "src long, dst long"))
    assert rows(publish_forest(vertices, result)) == rows(publish_forest(vertices, result, limit=0).select("vid", "parent", "root", "depth"))
    assert root_by_tours(spark.createDataFrame([], "comp long, src long, dst long")).count() == 0


def test_proxies_unfold_every_instance(spark):
    g, _ = sparse(spark, 40, 200, 6)
    e = spool.cut(msf.nested_instances(g.edges, 25))
    count = e.agg(F.max("first_instance")).first()[0]
    encoded = nested.encode_nested(e)
    deg = encoded.groupBy(F.col("u").alias("vid")).agg(F.count(F.lit(1)).alias("d"))
    for chunk in (1, 3, 1000):
        served = nested.expand_at_proxies(encoded, nested.assign_proxies(deg, 40, chunk), count)
        assert rows(served.where("u < v").select("instance", F.col("u").alias("src"), F.col("v").alias("dst"))) == rows(nested.expanded(e, count))
    one, two = (nested.components_of_nested(e, g.vertices, count, mode) for mode in ("parallel", "incremental"))
    sizes = lambda df: rows(df.groupBy("instance", "comp").count().groupBy("instance", "count").agg(F.count(F.lit(1)).alias("n")))
    assert sizes(one) == sizes(two)


def test_forests_by_both_methods(spark):
    g, _ = sparse(spark, 50, 300, 8)
    want = rows(msf.exact_local_msf(g).select("src", "dst"))
    for options in ({"method": "simultaneous"}, {"method": "simultaneous", "force_filter": True, "faithful": True}, {"method": "sequential"}):
        assert rows(msf.minimum_spanning_forest(g, **options).select("src", "dst")) == want
    for limit in (1000, 10):
        assert rows(msf.squared_growth_msf(g, limit=limit)[0].select("src", "dst")) == want


def test_tables_that_nothing_reads_are_deleted(spark):
    g, _ = sparse(spark, 30, 30, 9)
    before = set(spool._made())
    done = connected_components(g)
    made = set(spool._made()) - before
    assert done.labels.count() == 30 and done.forest.count() >= 0
    held = {p for p in made if any(p.rsplit("/", 1)[1] in f for df in (done.labels, done.forest) for f in df.inputFiles())}
    assert made == held and g.edges.count() > 0
