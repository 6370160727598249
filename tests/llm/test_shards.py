"""Writers and readers of one store at once, age of what vacuum deletes, and empty arrivals."""

import threading

from pyspark.sql import functions as F

from fewrounds.llm import shards


def test_two_writers_and_a_reader(spark, tmp_path):
    root, errors, seen = str(tmp_path / "store"), [], []
    stores = [shards.ShardStore(spark, root, target_bytes=1 << 20, fan_in=3) for _ in range(3)]
    halt = threading.Event()

    def write(store, who):
        try:
            for k in range(5):
                store.append(spark.range(100 * k, 100 * k + 100).select("id", F.lit(who).alias("who")), f"{who}-{k}")
                store.append(spark.range(100 * k, 100 * k + 100).select("id", F.lit(who).alias("who")), f"{who}-{k}")  # a restarted writer
                store.compact()
                store.vacuum()
        except Exception as e:  # noqa: BLE001
            errors.append(e)

    def read():
        try:
            while not halt.is_set():
                version = stores[2].version()
                if stores[2].shards(version):
                    seen.append((version, stores[2].read(version).count()))
        except Exception as e:  # noqa: BLE001
            errors.append(e)

    threads = [threading.Thread(target=write, args=(stores[k], k)) for k in range(2)]
    reader = threading.Thread(target=read)
    for t in (*threads, reader):
        t.start()
    for t in threads:
        t.join()
    halt.set()
    reader.join()
    assert not errors
    rows = stores[2].read()
    assert rows.count() == 1000 and rows.distinct().count() == 1000
    assert all(n % 100 == 0 for _, n in seen) and [n for _, n in sorted(seen)] == sorted(n for _, n in seen)
    names = [s.name for s in stores[2].shards()]
    assert len(set(names)) == len(names) and names == sorted(names)


def test_vacuum_deletes_by_age(spark, tmp_path):
    store = shards.ShardStore(spark, str(tmp_path / "store"), fan_in=2)
    for k in range(4):
        store.append(spark.range(10 * k, 10 * k + 10), str(k))
    lost = store._write(spark.range(5))  # a writer lost before its commit
    old = store.version()
    store.compact()
    store.vacuum()
    assert store.read(old).count() == 40 and store.read_files([s.file for s in lost]).count() == 5
    store.vacuum(older_than=-10)
    assert store.read().count() == 40 and {p.name for p in (tmp_path / "store" / "data").iterdir()} == {s.file.split("/")[0] for s in store.shards()}


def test_names_are_the_same_in_every_run(spark, tmp_path):
    docs = spark.range(200).select(F.col("id").alias("doc_id"), F.lit("t").alias("shard"), F.lit(None).cast("string").alias("text"))
    runs = []
    for k in range(2):
        store, rows = shards.sharded(docs, target_bytes=1 << 16, fan_in=3, root=str(tmp_path / str(k)))
        assert rows.count() == 200 and rows.columns == docs.columns
        runs.append([(s.name, s.tier) for s in store.shards()])
    assert runs[0] == runs[1]
    store, rows = shards.sharded(docs.where("false"), root=str(tmp_path / "empty"))
    assert rows.count() == 0 and rows.columns == docs.columns
