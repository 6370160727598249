from pyspark.sql import functions as F

from fewrounds.functions.coins import coin
from fewrounds.functions.params import params_for
from fewrounds.operators import graphs, sampling


def test_portable_samples_and_counted_messages(spark):
    g = graphs.generate_graph(spark, "path", 60).settle()
    p = params_for(g.n, seed=1)
    for chance in (p.p_edge, 0.0, 1.0):
        rows = sampling.sample_edges(sampling.with_leaders(g.edges, p, True), p.num_samples, chance, 1, portable=True)
        coins = g.edges.select("src", "dst", F.explode(F.sequence(F.lit(1), F.lit(p.num_samples))).alias("sample")).where(coin(1, "sample", "sample", "src", "dst", portable=True) < chance)
        assert sorted(tuple(r) for r in rows.select("src", "dst", "sample").collect()) == sorted(tuple(r) for r in coins.collect())
    labels, forest, messages = sampling.contract_by_samples(g, p, portable=True)
    counted = sampling.contract_by_samples(g, p, keep_messages=False, portable=True, count_messages=True)
    assert counted[2].agg(F.sum("held")).first()[0] == messages.count()
    assert sorted(counted[0].collect()) == sorted(labels.collect()) and sorted(counted[1].collect()) == sorted(forest.collect())
