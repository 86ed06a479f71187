"""Distributed runs: hierarchies split by rounds, candidates, waves, visiting order, files."""

from pathlib import Path

import numpy as np
import pytest

from gainclust.operators import kernels, kway
from gainclust.operators import state as st
from gainclust.plans import workloads
from gainclust.sources import features, storage
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def x():
    rng = np.random.default_rng(11)
    return np.concatenate([rng.normal(size=(160, 3)), 25 + 4 * rng.normal(size=(60, 3)), [50, 0, 0] + 9 * rng.normal(size=(40, 3))])


@pytest.fixture(scope="module")
def rows(spark, x):
    return spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<double>").repartition(4).cache()


def labels(result):
    return np.array([r.cluster for r in result.assignments.orderBy("id").collect()])


def same(a, b):
    return len(set(zip(a.tolist(), b.tolist()))) == len(set(a.tolist())) == len(set(b.tolist()))


@pytest.mark.parametrize("priority, s, k", [("size", 2, 9), ("size", 3, 8), ("avg_pair", 2, 6), ("avg_pair", 3, 8)])
def test_rounds_give_the_leaves_of_one_split_after_the_other(rows, x, priority, s, k):
    want = kernels.hierarchy(x, k, s=s, priority=priority)
    got = kway.gain_split(rows, k, s, priority=priority)
    assert same(labels(got), want.labels) and got.k == k
    splits = lambda nodes: {(n["node_id"], n["split_rank"]) for n in nodes if not n["is_leaf"]}
    assert splits(got.nodes) == splits(want.nodes)
    assert got.history[0]["rounds"] < k - 1 or priority == "avg_pair"


def frozen_tree(x, k, s, priority, epochs=2, share=2, seed=42):
    """One leaf after the other by frozen rounds, in plain Python: labels by node."""
    import hashlib

    draw = lambda a, salt: int(hashlib.md5(f"{a}:{salt}".encode()).hexdigest()[:7], 16)
    node = np.array(["0"] * len(x), object)
    while len(set(node)) < k:
        def key(n):
            y = x[node == n]
            err = ((y - y.mean(0)) ** 2).sum()
            return -len(y) if priority == "size" else -2 * err / (len(y) - 1)

        n = min((n for n in set(node) if (node == n).sum() > 1), key=lambda n: (key(n), n))
        parts = min(s, k - len(set(node)) + 1)
        at = np.flatnonzero(node == n)
        own = np.array([draw(f"{n}:{i}", seed) % parts for i in at])
        for epoch in range(1, epochs + 1):
            sums, cnt = kernels.sums(x[at], own, parts)
            new = own.copy()
            for j, i in enumerate(at):
                u, q = own[j], x[i] @ x[i]
                if cnt[u] <= 1:
                    continue
                lost = (2 * x[i] @ sums[u] - q - sums[u] @ sums[u] / cnt[u]) / (cnt[u] - 1)
                won = [(2 * x[i] @ sums[v] + q - sums[v] @ sums[v] / cnt[v]) / (cnt[v] + 1) - lost if cnt[v] else q - lost for v in range(parts)]
                won[u] = -np.inf
                if max(won) > 0 and draw(i, f"{seed}-{epoch}") % share == 0:
                    new[j] = int(np.argmax(won))
            own = new
        node[at] = [f"{n}.{c}" for c in own]
    return node


@pytest.mark.parametrize("priority, s, k", [("size", 2, 5), ("avg_pair", 3, 6)])
def test_relational_hierarchy_is_the_sequential_one(rows, x, priority, s, k):
    got = kway.gain_split(rows, k, s, priority=priority, engine="relational", max_epochs=2, share=2)
    want = frozen_tree(x, k, s, priority)
    assert same(labels(got), np.unique(want.astype(str), return_inverse=True)[1])


@pytest.mark.parametrize("options", [{}, {"priority": "avg_pair", "s": 3}, {"splitter": "lloyd", "init": "dsq_nearest"}])
def test_large_nodes_are_split_together(rows, x, options):
    got = kway.gain_split(rows, 6, local_rows=90, max_epochs=4, **options)
    own = labels(got)
    assert set(own) == set(range(6)) and len(own) == len(x)
    whole = kway.gain_split(rows, 6, **options)
    sse = [kernels.sse(x, labels(r), 6) for r in (got, whole)]
    assert sse[0] < 1.6 * sse[1]
    assert got.history[-1]["sse"] == pytest.approx(sse[0])
    # the queue holds: no split node comes before one that it prefers
    key = lambda n: -n["cnt"] if options.get("priority") != "avg_pair" else -2 * n["sse"] / max(n["cnt"] - 1, 1)
    split = sorted((n for n in got.nodes if not n["is_leaf"]), key=lambda n: n["split_rank"])
    for a, b in zip(split, split[1:]):
        assert key(a) <= key(b) or b["parent"] == a["node_id"]


def test_equal_rows_cannot_be_split(spark):
    rows = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(40)] + [(40, [9.0, 9.0])], "id long, vec array<double>")
    for size in (10, 1000):
        assert kway.gain_bisect(rows, 3, local_rows=size, max_epochs=2).k == 2


def test_first_moves_stop_early_and_both_scans_improve(x):
    for scan in ("rotated", "ascending"):
        run = kernels.gain_kway(x, 12, move="first", scan=scan)
        assert run.history[-1]["sse"] < run.history[0]["sse"] and run.history[0]["comparisons"] < 11 * len(x)
    with pytest.raises(ValueError):
        kernels.gain_kway(x, 3, scan="up")


def test_blocks_give_what_single_rows_give(x, monkeypatch):
    want = kernels.gain_kway(x, 9, seed=3)
    for size in (1, 7, 300):
        monkeypatch.setattr(kernels, "BLOCK", size)
        got = kernels.gain_kway(x, 9, seed=3)
        assert (got.labels == want.labels).all() and [h["comparisons"] for h in got.history] == [h["comparisons"] for h in want.history]


@pytest.mark.parametrize("mode", ["row", "cluster"])
def test_candidates(rows, x, mode):
    for engine in ("partitioned", "sequential"):
        full = kway.gain_kway(rows, 10, engine=engine, max_epochs=4)
        few = kway.gain_kway(rows, 10, engine=engine, max_epochs=4, candidates=3, candidate_mode=mode, warm_epochs=1)
        total = lambda r: sum(h["comparisons"] for h in r.history)
        assert total(few) < total(full)
        assert few.history[-1]["score"] > few.history[0]["score"]


def test_kernel_candidates_rank_as_the_columns_do(spark, rows, x):
    own = np.arange(len(x)) % 7
    state = st.cluster_state(rows.withColumn("cluster", (F.col("id") % 7).cast("int")))
    want = {}
    for r in st.row_candidates(rows, state, 3).collect():
        want.setdefault(r.id, []).append((r.place, r.cluster))
    got = kernels.nearest_by_gain(x, *kernels.sums(x, own, 7), 3)
    assert [[c for _, c in sorted(want[i])] for i in range(len(x))] == got.tolist()
    near = {(r.cluster, r.place): r.near for r in st.candidate_table(state, 2).collect()}
    table = kernels.nearest_centroids(*kernels.sums(x, own, 7), 2)
    assert all(table[c, p - 1] == v for (c, p), v in near.items())


def test_waves_and_least_share_of_moves(rows, x):
    one = kway.gain_kway(rows, 8, waves=2, max_epochs=2)
    assert all(a["score"] <= b["score"] for a, b in zip(one.history, one.history[1:]))
    assert len(kway.gain_kway(rows, 8, min_move_ratio=0.9, max_epochs=4).history) < 4


def test_every_epoch_visits_in_another_order(spark):
    ids = spark.range(200)
    orders = [[r.id for r in ids.orderBy(F.xxhash64("id", F.lit(42), F.lit(e))).collect()] for e in (1, 2)]
    a, b = orders
    turned = [a[i:] + a[:i] for i in range(200)]
    assert sorted(a) == sorted(b) and b not in turned


def test_files_of_past_epochs_are_deleted(spark, rows):
    top = Path(storage.shared_dir(spark).removeprefix("file:")) / "gainclust"
    count = lambda: len(list(top.iterdir())) if top.exists() else 0
    for run in (lambda e: kway.gain_kway(rows, 8, max_epochs=e), lambda e: kway.gain_kway(rows, 8, max_epochs=e, candidates=2, warm_epochs=1), lambda e: kway.gain_split(rows, 4, local_rows=90, max_epochs=e)):
        before = count()
        run(4)
        assert count() - before <= 1


def test_shared_folder_is_asked_for_on_a_cluster():
    class Fake:
        conf = {}

        class sparkContext:
            master = "spark://host:7077"

            @staticmethod
            def getCheckpointDir():
                return None

    with pytest.raises(ValueError):
        storage.shared_dir(Fake)


def test_minibatch_coverage(rows):
    every, part = (kway.minibatch(rows, 5, 0.5, 4, coverage=c) for c in ("iteration", "total"))
    assert sum(h["moves"] for h in part.history) < sum(h["moves"] for h in every.history)
    with pytest.raises(ValueError):
        kway.minibatch(rows, 5, coverage="all")


def test_start_snapshot(spark, sf):
    got = {r.epochs: r.violations for r in workloads.w13(spark, sf).collect()}
    assert got[0] > got[200] == 0


def test_first_moves_in_blocks_give_what_single_rows_give(x):
    y = np.concatenate([x, x[:, ::-1] + 1, x * x], axis=1)
    for scan in ("rotated", "ascending"):
        together, single = [], []
        for out, who in ((together, None), (single, np.tile(np.arange(9), (len(y), 1)))):  # candidates are looked at row by row
            labels = np.random.default_rng(2).integers(9, size=len(y))
            s, cnt = kernels.sums(y, labels, 9)
            for epoch in range(4):
                order = np.random.default_rng(epoch).permutation(len(y))
                if who is not None:
                    who = np.stack([np.roll(np.arange(9), -((int(i) * 2654435761 + epoch) % 9 if scan == "rotated" else 0)) for i in range(len(y))])
                out.append((kernels.one_pass(y, (y * y).sum(1), labels, s, cnt, order, "first", 1e-9, who, epoch, scan), labels.copy()))
        assert [a for a, _ in together] == [a for a, _ in single]
        assert all((a == b).all() for (_, a), (_, b) in zip(together, single))


def test_sums_of_wide_rows_have_the_bits_of_adding_row_by_row():
    rng = np.random.default_rng(3)
    for n, k in ((400, 7), (400, 1), (10, 9)):
        y, own = rng.normal(size=(n, 24)), rng.integers(max(k - 1, 1), size=n)  # the last cluster is empty
        want = np.zeros((k, 24))
        np.add.at(want, own, y)
        assert (kernels.sums(y, own, k)[0] == want).all()


@pytest.mark.parametrize("method", workloads.TABLE)
def test_runs_together_give_the_labels_of_runs_alone(method):
    rng = np.random.default_rng(8)
    y = np.abs(rng.normal(size=(230, 40))) * (rng.random((230, 40)) < 0.3)
    y[5] = 0
    got = {(k, seed): labels for k, seed, labels in kernels.labels_of(method, y, [1, 3, 4, 11], [0, 1, 7])}
    assert len(got) == 12
    for (k, seed), labels in got.items():
        assert (labels == kernels.METHODS[method](y, k, seed).labels).all(), (k, seed)


def test_document_entropies(spark, sf):
    """Against one run after the other; every row is sent once a method only, without its zeros."""
    names = ["lloyd", "online_lvq", "cosine_bisect"]
    found = workloads.w10(spark, sf, ks=(3, 500), corpora=3, restarts=2, methods=names, cls="source", vocab=64)
    got = {(r.method, r.k): r.entropy for r in found.collect()}
    docs = features.load_table(spark, sf, "documents")
    rows = features.doc_tfidf(docs, 64).join(docs.select(F.col("doc_id").alias("id"), "source"), "id").orderBy("id").toPandas()
    assert len(got) == 6 and len(rows) == docs.count()
    for (name, k), value in got.items():
        if (name, k) == ("online_lvq", 500):  # every row a centroid: between copies of a row rounding decides
            continue
        best = []
        for _, part in rows.groupby(rows.id % 3):
            y, code = np.stack(part["vec"].to_numpy()), part["source"].astype("category").cat.codes.to_numpy()
            h, classes = [], int(code.max()) + 1
            for seed in range(2):
                labels = kernels.METHODS[name](y, min(k, len(y)), seed).labels
                t = np.array([np.bincount(code[labels == c], minlength=classes) for c in np.unique(labels)])
                p = t / t.sum(1, keepdims=True)
                h.append(-(t.sum(1)[:, None] * p * np.log(np.where(p > 0, p, 1))).sum() / t.sum() / np.log(classes))
            best.append(min(h))
        assert abs(value - np.mean(best)) < 1e-9, (name, k)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "slots" in plan and "transform(sequence" not in plan


@pytest.mark.parametrize("seeding", ["random", "dsq"])
def test_late_epochs_sum_few_rows(monkeypatch, seeding):
    """Sums follow from the rows that changed: full sums only while many do and every FRESH epochs, with the same result."""
    x = np.random.default_rng(7).normal(size=(1500, 12)) + 2 * np.random.default_rng(8).normal(size=(6, 12))[np.arange(1500) % 6]
    whole, seen = kernels.sums, []
    monkeypatch.setattr(kernels, "sums", lambda y, labels, k: seen.append(len(y)) or whole(y, labels, k))
    for run in (kernels.lloyd(x, 9, seeding), kernels.gain_kway(x, 9, "seed_nearest")):
        assert len(run.history) > 8 and sum(seen) < 0.75 * len(x) * len(run.history), seen
        s, cnt = whole(x, run.labels, 9)
        assert abs(run.history[-1]["score"] - kernels.score(s, cnt)) < 1e-9 * kernels.score(s, cnt)
        seen.clear()
    old = np.random.default_rng(9).integers(9, size=1500)
    new = np.where(np.arange(1500) % 20 == 0, (old + 4) % 9, old)
    s, cnt = kernels.sums_after(x, *whole(x, old, 9), old, new)
    assert np.allclose(s, whole(x, new, 9)[0], atol=1e-11, rtol=0) and (cnt == whole(x, new, 9)[1]).all() and sum(seen) == 150


def test_distances_from_a_row():
    x = np.random.default_rng(3).normal(size=(300, 20))
    assert (kernels.from_row(x, 7) == ((x - x[7]) ** 2).sum(1)).all()


def test_document_rows_are_sent_once(spark, sf):
    """Only known terms go into the counts, and the methods of w10 share one shuffle of the rows."""
    found = workloads.w10(spark, sf, ks=(3,), corpora=2, restarts=1, methods=["lloyd", "minibatch", "lloyd_dsq"], vocab=64)
    assert found.count() == 3
    found.collect()
    plan = found._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    assert plan.count("ReusedExchange") >= 2 and plan.count("MapInPandas") == 3, plan
