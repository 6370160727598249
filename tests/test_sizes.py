"""What large tables need: fewer rows between stages, with the rows of the result unchanged."""

import random
import threading

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from fewrounds import queries
from fewrounds.functions.coins import coin
from fewrounds.functions.params import params_for
from fewrounds.operators import analysis, baselines, blocks, graphs, msf, nested, sampling, sketches
from fewrounds.operators.components import canonical_labels
from fewrounds.queries import QUERIES, SQL
from fewrounds.sources import derive


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def vectors(spark, tmp_path_factory):
    """60 vectors, some of them copies, so that distances tie."""
    r = np.random.default_rng(4)
    x = r.normal(size=(50, 8)).round(3)
    x = np.concatenate([x, x[:10]])
    d = str(tmp_path_factory.mktemp("vectors"))
    spark.createDataFrame([(int(k * 7 % 61), [float(v) for v in row]) for k, row in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(f"{d}/embeddings.parquet")
    e = [(a["vec_id"], np.array(a["embedding"])) for a in spark.read.parquet(f"{d}/embeddings.parquet").collect()]
    pairs = [(min(i, j), max(i, j), float(np.floor((1 - u @ v / np.sqrt((u @ u) * (v @ v))) * 1e9 + 0.5)) / 1e9) for i, u in e for j, v in e if i < j]
    return d, pairs


@pytest.mark.parametrize("block", [7, 30, 2048])
def test_forest_of_vectors_without_all_pairs(spark, vectors, block):
    d, pairs = vectors
    every = graphs.build(spark.createDataFrame(pairs, "src long, dst long, weight double"), weight="weight")
    g = derive.embedding_pairs(spark, d, block=block)
    assert g.edges.count() < len(pairs) and g.n == 60
    assert rows(msf.exact_local_msf(g)) == rows(msf.exact_local_msf(every))


@pytest.mark.parametrize("block", [7, 2048])
def test_nearest_vectors_by_blocks(spark, vectors, block):
    d, pairs = vectors
    near = {}
    for a, b, w in pairs:
        near.setdefault(a, []).append((w, b))
        near.setdefault(b, []).append((w, a))
    want = sorted({(min(a, b), max(a, b), w) for a, of in near.items() for w, b in sorted(of)[:3]})
    assert rows(derive.embedding_knn(spark, d, block=block).edges) == want


@pytest.fixture(scope="module")
def suppliers(spark, tmp_path_factory):
    """Suppliers of whom many have one balance, as copies of a table have."""
    r = random.Random(3)
    d = str(tmp_path_factory.mktemp("suppliers"))
    keys = r.sample(range(1000), 60)
    spark.createDataFrame([(k, r.choice((-5.25, 0.1, 0.2, 0.3, 17.04, 900.91, 9999.99))) for k in keys], "s_suppkey long, s_acctbal double").write.parquet(f"{d}/supplier.parquet")
    return d


def by_sql(d, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW supplier AS SELECT * FROM '{d}/supplier.parquet/*.parquet'")
    return sorted(con.execute(f"SELECT src, dst, weight FROM ({SQL[name]})").fetchall())


@pytest.mark.parametrize("name", ["msf_supplier_line", "msf_uniform_runs"])
def test_forests_of_suppliers_with_equal_balances(spark, suppliers, name):
    assert rows(QUERIES[name](spark, suppliers)) == by_sql(suppliers, name)


def test_suppliers_too_close_to_tell_keep_all_pairs(spark, tmp_path):
    x = [1.0, 1.0 + 2.0**-52, 1.0 + 2.0**-51, 2.0, 4096.0]
    spark.createDataFrame([(9 - k, v) for k, v in enumerate(x)], "s_suppkey long, s_acctbal double").write.parquet(f"{tmp_path}/supplier.parquet")
    assert derive.supplier_levels(spark, str(tmp_path)).edges.count() == 10


def test_schedule_and_parameters_follow_the_tables(spark):
    d = "/root/testdata/sf0.001"
    rounds = QUERIES["auxiliary_schedule"](spark, d).collect()
    assert len(rounds) == 16 and sum(r["messages"] for r in rounds) == derive.order_part(spark, d).edges.count()
    assert {r["source"]: r["n"] for r in QUERIES["params_table"](spark, d).collect()}["orders"] == 1500


@pytest.mark.parametrize("block", [5, 2048])
def test_forest_and_components_of_user_hours_without_all_pairs(spark, tmp_path, block):
    r, d = random.Random(6), str(tmp_path)
    spark.createDataFrame([(k, r.randrange(40), 3600 * (r.randrange(25) + 100 * r.randrange(2))) for k in range(150)], "event_id long, user_id long, at long").select("event_id", "user_id", F.timestamp_seconds("at").cast("timestamp_ntz").alias("ts")).write.parquet(f"{d}/events.parquet")
    every, some, links = derive.user_hour(spark, d), derive.user_hour_pairs(spark, d, block), derive.user_hour_links(spark, d)
    assert some.edges.count() < every.edges.count() and rows(some.vertices) == rows(every.vertices) == rows(links.vertices)
    assert rows(msf.exact_local_msf(some)) == rows(msf.exact_local_msf(every))
    assert rows(baselines.exact_local_cc(links).labels) == rows(baselines.exact_local_cc(every).labels)


def test_users_travel_once_a_strip_and_edges_are_made_once(spark, tmp_path, monkeypatch):
    r, d = random.Random(8), str(tmp_path)
    spark.createDataFrame([(k, r.randrange(60), 3600 * (r.randrange(30) + 2000 * r.randrange(2))) for k in range(400)], "event_id long, user_id long, at long").select("event_id", "user_id", F.timestamp_seconds("at").cast("timestamp_ntz").alias("ts")).write.parquet(f"{d}/events.parquet")
    every = derive.user_hour(spark, d)
    monkeypatch.setattr(derive, "LEAST_STRIPS", 2)
    some = derive.user_hour_pairs(spark, d, 8, 4)
    assert some.edges.count() <= 3 * 59  # three tasks, each hands on a forest
    want = rows(msf.exact_local_msf(every))
    assert rows(msf.exact_local_msf(some)) == want
    made = spark.sparkContext.accumulator(0)

    def noted(batches):
        for batch in batches:
            made.add(batch.num_rows)
            yield batch

    count = some.edges.count()
    seen = graphs.EdgeSet(some.vertices, some.edges.mapInArrow(noted, some.edges.schema))
    assert rows(msf.hook_and_contract_msf(seen)) == want and made.value == count


def test_forests_of_msf_instances_are_made_side_by_side(spark, monkeypatch):
    meet = threading.Barrier(3, timeout=30)

    def forest(g, log):
        meet.wait()
        log["instances"] = [g]
        return spark.range(g)

    monkeypatch.setattr(msf, "minimum_spanning_forest", forest)
    monkeypatch.setattr(queries, "FORESTS", {f"g{k}": lambda spark, d, k=k: k for k in range(1, 4)})
    assert [tuple(r) for r in QUERIES["msf_instances"](spark, "").collect()] == [(f"g{k}", k, [k], None, None) for k in range(1, 4)]


@pytest.mark.parametrize("kind", ["path", "grid", "tree"])
def test_messages_by_joins_take_only_what_is_open(spark, monkeypatch, kind):
    r = random.Random(2)
    names = r.sample(range(10_000), 80)
    ids = spark.createDataFrame(list(enumerate(names)), "id long, vid long").cache()
    e = graphs.generate_graph(spark, kind, 80).edges.join(ids.select(F.col("id").alias("src"), F.col("vid").alias("a")), "src").join(ids.select(F.col("id").alias("dst"), F.col("vid").alias("b")), "dst")
    g = graphs.build(e.select(F.col("a").alias("src"), F.col("b").alias("dst")))
    p = params_for(80, seed=1, num_samples=2, p_edge=0.9, p_leader=0.05)
    samples = sampling.sample_edges(g.edges, 2, 0.9, 1, portable=True)
    seen, rests = sampling.cut, []

    def noted(df):
        out = seen(df)
        if df.columns == ["sample", "v", "u"]:
            rests.append(out.count())
        return out

    monkeypatch.setattr(sampling, "cut", noted)
    found = rows(sampling.solve_samples_by_joins(samples, p, portable=True).fillna(-1))
    assert len(rests) > 2 and rests[-1] == 0 and all(a > b for a, b in zip(rests, rests[1:], strict=False))
    want = sampling.solve_sample(samples, p, portable=True).fillna(-1)
    assert found == rows(want)


def test_pieces_of_random_forests():
    r = random.Random(1)
    for k in range(400):
        n, back, s = r.randrange(2, 60), r.choice([1, 2, 3, 10, 60]), r.randrange(1, 8)
        names = r.sample(range(1000), n)
        edges = [(names[i], names[0 if k % 7 == 0 else max(0, i - r.randrange(1, back + 1))]) for i in range(1, n) if k % 3 or r.random() < 0.9]
        if not edges:
            continue
        near: dict = {}
        for a, b in edges:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)

        def reach(v, inside, near=near):
            seen, stack = {v}, [v]
            while stack:
                new = {y for y in near[stack.pop()] if y in inside} - seen
                seen |= new
                stack += new
            return seen

        ids, piece, at, unique = analysis._tiles(*(np.array(x) for x in zip(*edges, strict=True)), s)
        pieces, places = {}, {}
        for p, v, u in zip(piece.tolist(), ids[at].tolist(), unique.tolist(), strict=True):
            pieces.setdefault(p, {})[v] = u
            places.setdefault(v, []).append(u)
        assert set(places) == set(near) and len(piece) == sum(map(len, pieces.values()))
        assert all(len(x) == 1 and x[0] or len(x) > 1 and not any(x) for x in places.values())
        for own in pieces.values():
            v = next(iter(own))
            assert reach(v, own) == set(own) and sum(not u for u in own.values()) <= 1
            assert len(own) <= 3 * s and (len(own) >= s or set(own) == reach(v, near))


def test_pieces_verdict_needs_no_forest_from_one_task(spark, monkeypatch):
    def never(g):
        raise AssertionError("all edges in one task")

    monkeypatch.setattr(baselines, "exact_local_cc", never)
    assert all(r["least_ok"] and r["most_ok"] and r["shared_ok"] for r in QUERIES["almost_partition_verdict"](spark, "/root/testdata/sf0.001").collect())


def test_least_forest_of_a_matrix_with_gaps():
    far = np.iinfo(np.int64).max
    keys = np.full((4, 4), far)
    for k, (i, j) in enumerate(((0, 1), (2, 3))):
        keys[i, j] = keys[j, i] = k + 5
    assert sorted(derive._sparsest(keys, True).tolist()) == [5, 6]
    assert sorted(derive._sparsest(np.array([[1, far, far], [far, 2, 3]]), False).tolist()) == [1, 2, 3]


def test_sketches_by_joins_write_one_repetition_at_a_time(spark, monkeypatch):
    written = []

    def noted(f):
        def run(df):
            if "rep" in df.columns:
                written.append(df.select("rep").distinct().count())
            return f(df)

        return run

    for name in ("cut", "cut_and_count"):
        monkeypatch.setattr(sketches, name, noted(getattr(sketches, name)))
    g = graphs.generate_graph(spark, "sparse", 300).settle()
    alone, log = g.vertices.select("vid", F.col("vid").alias("comp")), []
    done = sketches.finish_by_sketches(g, alone, g.edges.where("false"), task_limit=0, log=log)
    want = rows(baselines.exact_local_cc(g).labels)
    assert rows(canonical_labels(g.vertices, done.labels)) == want and done.forest.count() == 300 - len({c for _, c in want})
    assert len(log) > 1 and max(written) == 1


@pytest.mark.parametrize("kind", ["sparse", "grid"])
def test_samples_drawn_in_their_tasks(spark, monkeypatch, kind):
    monkeypatch.setattr(blocks, "CHUNK", 64)
    g = graphs.generate_graph(spark, kind, 200).settle()
    p = params_for(g.n, seed=2, num_samples=23, p_edge=0.4, p_leader=0.05)
    edges = sorted(rows(g.edges.select("src", "dst")))
    drawn = [(k, *edges[i]) for k in range(1, 24) for i in blocks.drawn(p.seed, k, len(edges), p.p_edge)]
    assert 0.3 < len(drawn) / (23 * len(edges)) < 0.5
    samples = spark.createDataFrame(drawn, "sample int, src long, dst long")
    led = {v for (v,) in rows(g.vertices.where(coin(p.seed, "leader", "vid") < p.p_leader))}
    want = {(v, hop) for v, hop in sampling.best_message(sampling.solve_sample(samples, p)).collect() if v not in led}
    for count in (1, 5, None):
        got = blocks.best_hops(g.edges.repartition(3), p, count).collect()
        assert len(got) == len(want) and set(map(tuple, got)) == want


def test_more_samples_than_may_be_dealt_are_not_written(spark, monkeypatch):
    def dealt(*_):
        raise AssertionError("the edges of all samples were dealt")

    monkeypatch.setattr(sampling, "best_of_samples", dealt)
    g = graphs.generate_graph(spark, "sparse", 200).settle()
    labels, forest, _ = sampling.contract_by_samples(g, params_for(g.n), keep_messages=False, dealt_limit=10)
    assert rows(forest.join(g.edges, ["src", "dst"], "left_semi")) == rows(forest)
    assert labels.count() == 200 and labels.select("comp").distinct().count() == 200 - forest.count()


def test_instances_unfold_only_edges_that_join(spark, suppliers, monkeypatch):
    g = derive.supplier_line(spark, suppliers).settle()
    e = msf.nested_instances(g.edges, g.n).cache()
    last = e.agg(F.max("first_instance")).first()[0]
    want = rows(nested.components_of_nested(e, g.vertices, last, unfold_limit=1 << 40))
    unfolded, whole = [], nested.union_of_nested
    monkeypatch.setattr(nested, "union_of_nested", lambda edges, *rest: unfolded.append(edges.count()) or whole(edges, *rest))
    assert last > 20 and rows(nested.components_of_nested(e, g.vertices, last, unfold_limit=0)) == want
    assert unfolded == [59]
    for limit in (100, 500):
        some = nested.joining_edges(e, last, limit)
        assert 59 <= some.count() < e.count()
        for k in (1, 2, 5, last):
            full, few = (baselines.exact_local_cc(graphs.EdgeSet(g.vertices, x.where(F.col("first_instance") <= k).select("src", "dst"))) for x in (e, some))
            assert rows(full.labels) == rows(few.labels)


@pytest.mark.parametrize("kind", ["suppliers", "sparse"])
def test_sparsification_of_instances_in_tasks(spark, suppliers, monkeypatch, kind):
    g = derive.supplier_line(spark, suppliers).settle() if kind == "suppliers" else graphs.generate_graph(spark, "hubs", 8).settle()
    e = g.edges if kind == "suppliers" else g.edges.withColumn("weight", coin(1, "w", "src", "dst"))
    e = msf.nested_instances(e, 60).cache()
    last = e.agg(F.max("first_instance")).first()[0]
    for s, count in ((3, last), (5, min(3, last))):
        union, split = nested.nested_sparsify(e.where(F.col("first_instance") <= count), g.vertices, count, s)
        want = rows(analysis.split_measures(union, split, s))
        assert rows(nested.nested_split_measures(e, g.vertices, count, s)) == rows(nested.nested_split_measures(e, g.vertices, count, s, 2)) == want
    if kind == "suppliers":
        monkeypatch.setattr(nested, "UNFOLD_LIMIT", 0)
        monkeypatch.setattr(nested, "nested_sparsify", None)  # no instances side by side
        con = duckdb.connect()
        con.execute(f"CREATE VIEW supplier AS SELECT * FROM '{suppliers}/supplier.parquet/*.parquet'")
        assert rows(QUERIES["nested_sparsify_all"](spark, suppliers)) == con.execute(SQL["nested_sparsify_all"]).fetchall()


def test_instances_by_levels_and_run_by_run(spark, suppliers, monkeypatch):
    """both ways give the components of one graph of all instances, without such a graph and without joins a run."""
    g = derive.supplier_line(spark, suppliers).settle()
    e = msf.nested_instances(g.edges, g.n).cache()
    last = e.agg(F.max("first_instance")).first()[0]
    want = {k: rows(nested.components_of_nested(e, g.vertices, k, side_limit=1 << 40)) for k in (5, last)}
    sides, whole = [], nested.connected_components
    monkeypatch.setattr(nested, "connected_components", lambda union: sides.append(union.n) or whole(union))
    monkeypatch.setattr(nested, "relabel", None)
    for k, limit in ((5, 0), (last, 6 * 60)):
        assert rows(nested.components_of_nested(e, g.vertices, k, side_limit=limit)) == want[k]
        assert rows(nested.components_of_nested(e, g.vertices, k, "incremental")) == want[k]
    assert max(sides) <= 6 * 60 < last * 60
    ways, way = [], nested.components_of_nested
    monkeypatch.setattr(nested, "components_of_nested", lambda *a, **k: ways.append(a[3] if len(a) > 3 else "parallel") or way(*a, **k))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW supplier AS SELECT * FROM '{suppliers}/supplier.parquet/*.parquet'")
    assert rows(QUERIES["nested_labels_all"](spark, suppliers)) == sorted(con.execute(SQL["nested_labels_all"]).fetchall())
    assert ways[:2] == ["incremental", "parallel"]


def test_run_by_run_from_any_block(spark):
    e = spark.createDataFrame([(5, 9, 1), (2, 9, 3), (3, 4, 3), (2, 3, 6)], "src long, dst long, first_instance int")
    v = spark.createDataFrame([(x,) for x in (1, 2, 3, 4, 5, 9)], "vid long")
    want = rows(nested._run_by_run(e, v, 7, 1))
    assert len(want) == 42 and {c for i, x, c in want if i == 7} == {1, 2} and {c for i, x, c in want if i == 3 and x in (5, 9)} == {2}
    assert all(rows(nested._run_by_run(e, v, 7, k)) == want for k in (2, 7, 9))


@pytest.mark.parametrize("kind", ["path", "grid", "tree", "sparse"])
def test_samples_in_parts_give_the_messages_of_whole_samples(spark, monkeypatch, kind):
    """a sample is solved part by part, and components over several parts are found whole."""
    monkeypatch.setattr(blocks, "PART", 40)
    g = graphs.generate_graph(spark, kind, 300).settle()
    p = params_for(g.n, seed=2, num_samples=15, p_edge=0.6, p_leader=0.1)
    leader = {v for (v,) in rows(g.vertices.where(coin(p.seed, "leader", "vid") < p.p_leader))}
    src, dst = (np.array(x) for x in zip(*rows(g.edges.select("src", "dst")), strict=True))
    ids, vertices, a, b, starts, begins = blocks._laid(src, dst)
    assert sorted(vertices.tolist()) == list(range(len(ids))) and max(np.diff(starts)) < len(ids) / 2 and begins[-1] == len(src)
    assert begins[-1] - begins[-2] < len(src) / 2 and (kind == "sparse") == (begins[-1] == begins[-2])
    seen, whole = [], blocks._pointers
    monkeypatch.setattr(blocks, "_pointers", lambda u, v, own, *rest: seen.append(len(own)) or whole(u, v, own, *rest))
    leads = np.array([(x in leader) + 2 * (y in leader) for x, y in zip(src.tolist(), dst.tolist(), strict=True)])
    got, best, hops = blocks._best(range(1, 16), src, dst, leads, p)
    assert len(seen) > 15
    far = [ids[vertices[z]] for z in (a, b)]
    drawn = [(k, int(min(far[0][i], far[1][i])), int(max(far[0][i], far[1][i]))) for k in range(1, 16) for i in blocks.drawn(p.seed, k, len(a), p.p_edge)]
    samples = spark.createDataFrame(drawn, "sample int, src long, dst long")
    want = {(v, hop) for v, hop in sampling.best_message(sampling.solve_sample(samples, p)).collect() if v not in leader}
    assert {(int(v), None if h < 0 else int(got[h])) for v, x, h in zip(got, best, hops, strict=True) if x > 0} == want
