"""Hand-computed answers, identities and properties of the clustering engine."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from gainclust import registry
from gainclust.functions import vectors
from gainclust.operators import kernels, kway, metrics, pq
from gainclust.operators import state as st
from gainclust.sources import features, storage
from gainclust.streaming import streams


def frame(spark, values, labels):
    return spark.createDataFrame([(i, [float(v)] if np.isscalar(v) else [float(x) for x in v], c) for i, (v, c) in enumerate(zip(values, labels))], "id long, vec array<double>, cluster int")


def test_swap4(spark):
    rows = frame(spark, [0, 10, 0, 10], [0, 0, 1, 1])
    s = st.cluster_state(rows)
    o = st.objectives(s).first()
    assert (o.total, o.score, o.sse, o.pair_exact, o.pair_approx) == (200, 100, 100, 400, 200)
    assert [r.pair_sum for r in st.pair_measures(s).collect()] == [100, 100]
    assert all(abs(r.gain - 100 / 3) < 1e-9 and r.exact for r in st.gains(rows, s).collect())
    for engine in ("relational", "partitioned", "sequential"):
        got = kway.gain_kway(rows.select("id", "vec"), 2, rows.select("id", "cluster"), engine=engine)
        assert st.objectives(got.state(rows)).first().sse == 0, engine


def test_single_and_empty(spark):
    rows = frame(spark, [5, 1, 3], [0, 1, 1])
    s = st.cluster_state(rows)
    g = {(r.id, r.v): r.gain for r in st.gains(rows, s).collect()}
    assert abs(g[0, 1] + 6) < 1e-9 and st.best_moves(rows, s).where("id = 0").count() == 0
    rows = frame(spark, [0, 4], [0, 0])
    s = st.padded(st.cluster_state(rows), 2, 1)
    assert [r.gain for r in st.gains(rows, s).collect()] == [8, 8]


def test_gain_is_the_change_of_score():
    rng = np.random.default_rng(0)
    x, k = rng.normal(size=(40, 3)), 5
    labels = rng.integers(k, size=40)
    for i in range(40):
        u = labels[i]
        before = kernels.score(*kernels.sums(x, labels, k))
        best = max((kernels.score(*kernels.sums(x, np.where(np.arange(40) == i, v, labels), k)) - before, -v) for v in range(k) if v != u)
        s, cnt = kernels.sums(x, labels, k)
        own = labels.copy()
        kernels.one_pass(x, (x * x).sum(1), own, s, cnt, np.array([i]), "best", 0.0)
        if cnt.min() > 0 and (labels == u).sum() > 1 and best[0] > 1e-9:
            assert own[i] == -best[1]
        assert np.allclose(s, kernels.sums(x, own, k)[0])


@pytest.mark.parametrize("move", ["best", "first"])
@pytest.mark.parametrize("init", ["random_label", "seed_nearest", "dsq_nearest"])
def test_kernel_properties(init, move):
    x = np.random.default_rng(1).normal(size=(150, 4))
    run = kernels.gain_kway(x, 6, init, move, 200)
    scores = [h["score"] for h in run.history]
    assert all(a < b + 1e-12 for a, b in zip(scores, scores[1:])) and run.history[-1]["moves"] == 0
    # a fixed point satisfies the nearest-centroid condition
    c = run.centroids(x)
    d2 = ((x[:, None] - c[None]) ** 2).sum(2)
    assert (d2.argmin(1) == run.labels).all()


def test_candidates_full_width_is_exact():
    x = np.random.default_rng(2).normal(size=(100, 4))
    assert (kernels.gain_kway(x, 8, candidates=8).labels == kernels.gain_kway(x, 8).labels).all()
    assert len(np.unique(kernels.gain_kway(x, 8, candidates=2).labels)) == 8


def test_hierarchy():
    x = np.random.default_rng(3).normal(size=(120, 3))
    run = kernels.hierarchy(x, 7)
    assert len(np.unique(run.labels)) == 7
    split = sorted((n for n in run.nodes if not n["is_leaf"]), key=lambda n: n["split_rank"])
    sizes = [n["cnt"] for n in split]
    assert sizes == sorted(sizes, reverse=True) and len(split) == 6
    assert len(np.unique(kernels.hierarchy(x, 7, s=3).labels)) == 7
    better = kernels.gain_kway(x, 7, run.labels)
    assert better.history[-1]["sse"] <= run.history[-1]["sse"] + 1e-9
    with pytest.raises(ValueError):
        kernels.hierarchy(x, 7, move="first")
    assert len(np.unique(kernels.hierarchy(np.ones((5, 2)), 3).labels)) == 1


def test_cosine_is_the_gain_hierarchy_on_unit_rows():
    x = kernels.unit_rows(np.random.default_rng(4).normal(size=(90, 5)))
    assert (kernels.METHODS["cosine_bisect"](x, 5, 1).labels == kernels.METHODS["gain_bisect_seed_nearest"](x, 5, 1).labels).all()


@pytest.mark.parametrize("method", list(kernels.METHODS))
def test_every_method(method):
    x = np.concatenate([np.random.default_rng(5).normal(size=(40, 3)) + 20 * i for i in range(3)])
    run = kernels.METHODS[method](x, 3, 1)
    assert len(run.labels) == 120 and run.labels.min() >= 0 and run.labels.max() < 3
    for k in (1, 120):
        assert len(kernels.METHODS[method](x, k, 1).labels) == 120


def test_bad_arguments(spark):
    rows = frame(spark, [1, 2], [0, 0])
    with pytest.raises(ValueError):
        kway.gain_kway(rows, 3)
    with pytest.raises(ValueError):
        kway.gain_split(rows, 2, move="first")
    with pytest.raises(ValueError):
        kernels.gain_kway(np.ones((2, 1)), 1, "nothing")
    with pytest.raises(ValueError):
        pq.split_subvectors(rows, 2, 3)
    with pytest.raises(ValueError):
        st.padded(st.cluster_state(rows), 1 << 20, 1 << 10)


def test_validation(spark):
    bad = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0, None]), (4, [float("nan"), 0.0]), (5, [float("inf"), 0.0])], "id long, vec array<double>")
    assert [r.id for r in vectors.validate(bad, "skip").collect()] == [1]
    assert vectors.validate(bad, "quarantine").where("usable").count() == 1
    with pytest.raises(ValueError):
        vectors.validate(bad)
    assert vectors.validate(bad.where("false")).count() == 0


def test_engines_agree_on_quality(spark, sf):
    rows = features.emb64_scaled(spark, sf).select("id", "vec")
    sse = {e: st.objectives(kway.gain_kway(rows, 8, engine=e, max_epochs=6, share=2).state(rows)).first().sse for e in ("relational", "partitioned", "sequential")}
    assert max(sse.values()) < 1.05 * min(sse.values()), sse


def test_guard_raises_the_score(spark):
    x = np.random.default_rng(6).normal(size=(60, 2))
    rows = frame(spark, list(x), [0] * 60).select("id", "vec").repartition(4)
    for engine in ("relational", "partitioned"):
        got = kway.gain_kway(rows, 4, engine=engine, max_epochs=8)
        scores = [h["score"] for h in got.history]
        assert all(a <= b + 1e-9 for a, b in zip(scores, scores[1:]))
        assert got.assignments.count() == 60 and got.assignments.select("id").distinct().count() == 60


def test_distributed_hierarchy(spark):
    x = np.concatenate([np.random.default_rng(7).normal(size=(50, 2)) + 30 * i for i in range(4)])
    rows = frame(spark, list(x), [0] * 200).select("id", "vec")
    got = kway.gain_bisect(rows, 4, local_rows=120)
    assert got.assignments.groupBy("cluster").count().count() == 4 and got.assignments.count() == 200


def test_lloyd_and_minibatch(spark):
    x = np.concatenate([np.random.default_rng(8).normal(size=(50, 2)) + 30 * i for i in range(3)])
    rows = frame(spark, list(x), [0] * 150).select("id", "vec")
    assert st.objectives(kway.lloyd(rows, 3, "dsq").state(rows)).first().distortion < 5
    assert kway.minibatch(rows, 3, 0.3, 5).assignments.count() == 150


def test_entropy(spark):
    a = spark.createDataFrame([(i, i // 4) for i in range(8)], "id long, cluster int")
    pure = spark.createDataFrame([(i, str(i // 4)) for i in range(8)], "id long, cls string")
    mixed = spark.createDataFrame([(i, str(i % 2)) for i in range(8)], "id long, cls string")
    assert metrics.total_entropy(metrics.entropy(a, pure)).first().entropy == 0
    assert abs(metrics.total_entropy(metrics.entropy(a, mixed)).first().entropy - 1) < 1e-12


def test_measures(spark):
    assert [round(metrics.nominal_comparisons(1024, 16, s)) for s in (2, 4, 16)] == [4096, 6144, 15360]
    assert [round(kernels.lvq_rate(i), 6) for i in (0, 10, 25, 30)] == [0.01, 0.006, 0, 0]
    runs = spark.createDataFrame([("a", 1, 2.0), ("a", 2, 4.0), ("b", 1, 1.0), ("b", 2, 1.0)], "method string, n int, seconds double")
    assert {r.method: round(r.slope, 6) for r in metrics.growth(runs, "n", "seconds").collect()} == {"a": 1.0, "b": 0.0}
    assert {r.method: r.ratio for r in metrics.speedup(runs, "a").collect()} == {"a": 1.0, "b": 3.0}
    a = spark.createDataFrame([(i, i % 3) for i in range(30)], "id long, cluster int")
    assert abs(metrics.pair_agreement(a, a.withColumn("cluster", 2 - F.col("cluster"))).first().rand - 1) < 1e-12


def test_search(spark, sf):
    rows = features.emb64(spark, sf)
    q, base = rows.where("id % 10 = 0"), rows.where("id % 10 <> 0")
    truth = pq.exact_knn(q, base, 5)
    assert pq.recall_at(truth, truth, [1, 5]).where("recall = 1").count() == 2
    books = pq.train_pq(base, 8, 64, 64)
    got = pq.adc_search(q, pq.pq_encode(base, books, 8, 64), books, 8, 50)
    curve = [r.recall for r in pq.recall_at(got, truth, [1, 10, 50]).orderBy("rank").collect()]
    assert curve == sorted(curve) and curve[-1] > 0.8


def test_lossless_quantizer(spark):
    x = np.random.default_rng(9).integers(0, 3, size=(60, 4)).astype(float)
    rows = frame(spark, list(x), [0] * 60).select("id", "vec")
    words = pq.split_subvectors(rows, 2, 4).select("sub", "vec").distinct()
    from pyspark.sql import Window

    books = words.withColumn("code", F.row_number().over(Window.partitionBy("sub").orderBy("vec")) - 1)
    back = pq.pq_decode(pq.pq_encode(rows, books, 2, 4), books, 2)
    assert pq.pq_error(rows, back).first().mean_error == 0


def test_model_io(spark, tmp_path):
    rows = frame(spark, [1, 2, 8, 9], [0, 0, 1, 1])
    s = st.cluster_state(rows)
    storage.save_model(f"file://{tmp_path}/m", {"state": s}, {"k": 2})
    tables, params = storage.load_model(spark, f"file://{tmp_path}/m")
    assert params == {"k": 2} and sorted(map(tuple, tables["state"].collect())) == sorted(map(tuple, s.collect()))
    storage.write_assignments(rows.select("id", "cluster"), f"file://{tmp_path}/a")
    assert spark.read.parquet(f"file://{tmp_path}/a").where("cluster = 1").count() == 2


def test_streams(spark, sf, tmp_path):
    rows = features.part2(spark, sf)
    state = storage.stored(st.cluster_state(rows.select("id", "vec", F.col("label").cast("int").alias("cluster"))), "state")
    rows.select("id", "vec").repartition(3).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("id long, vec array<double>").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = streams.score_stream(stream, state).writeStream.format("memory").queryName("scored").start()
    q.processAllAvailable()
    q.stop()
    want = {(r.id, r.cluster) for r in st.assign_nearest(rows, state).collect()}
    assert {(r.id, r.cluster) for r in spark.table("scored").collect()} == want
    state.write.parquet(f"{tmp_path}/states/batch=-1")
    q = stream.writeStream.foreachBatch(streams.Absorber(f"{tmp_path}/states")).option("checkpointLocation", f"{tmp_path}/cp").start()
    q.processAllAvailable()
    q.stop()
    last = spark.read.parquet(f"{tmp_path}/states/batch=2")
    total = st.objectives(state).first()
    after = st.objectives(last).first()
    assert after.n == 2 * total.n and abs(after.total - 2 * total.total) < 1e-6 * total.total


def test_late_events_are_dropped(spark, tmp_path):
    from datetime import datetime, timedelta

    t0 = datetime(2024, 1, 1)
    lots = [[(1, t0, 7, "click", 1.0), (2, t0 + timedelta(days=2), 7, "view", 2.0)], [(3, t0 + timedelta(minutes=1), 7, "click", 9.0), (2, t0 + timedelta(days=2), 7, "view", 2.0)], [(4, t0 + timedelta(days=4), 8, "error", 1.0)]]
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double"
    frames = [spark.createDataFrame(lot, schema).coalesce(1) for lot in lots]
    for name, query in (("windows", streams.user_windows), ("firsts", streams.first_events)):
        frames[0].where("false").write.parquet(f"{tmp_path}/{name}")
        q = query(spark.readStream.schema(schema).parquet(f"{tmp_path}/{name}")).writeStream.format("memory").queryName(name).outputMode("append").start()
        for f in frames:
            f.write.mode("append").parquet(f"{tmp_path}/{name}")
            q.processAllAvailable()
        q.stop()
    assert {(r.user_id, r.start): r.click for r in spark.table("windows").collect()}[7, t0] == 1
    assert sorted(r.event_id for r in spark.table("firsts").collect()) == [1, 2, 4]


def test_plans(spark, sf):
    rows = features.emb64(spark, sf).select("id", "vec", F.col("label").alias("cluster"))
    text = lambda df: df._jdf.queryExecution().toString()
    near = text(st.assign_nearest(rows, st.cluster_state(rows)))
    assert "BroadcastNestedLoopJoin" in near and "Python" not in near
    scan = text(features.cust4(spark, sf))
    assert "ReadSchema: struct<o_custkey:bigint,o_totalprice:double>" in scan
    assert "Python" not in text(registry.gain_all_pairs(spark, sf))


def test_tables_vectors(spark, sf):
    assert features.line4(spark, sf).select("id").distinct().count() == spark.read.parquet(f"{sf}/lineitem.parquet").count()
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    vec = features.doc_tfidf(docs, 64)
    assert vec.count() == docs.count() and vec.where(F.size("vec") != 64).isEmpty()
    assert features.doc_hashed(docs).count() <= docs.count()
    assert features.grown(features.part2(spark, sf), 3).select("id").distinct().count() == 600


def test_entry(spark, sf):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert sum(r.cnt for r in rows) == 500 and set(e.oracle_sql()) <= set(e.queries())
    assert math.isclose(sum(r.sse for r in rows), sum(r.sse for r in e.entry(spark).collect()))
