"""The experiments, each a DataFrame of one row per method and setting."""

from __future__ import annotations

import time
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainclust.functions.vectors import root_normalize, unit
from gainclust.operators import kernels, kway, metrics, pq, state
from gainclust.operators.kway import LOCAL_ROWS, _matrix
from gainclust.sources import features
from gainclust.sources.storage import load_table

KWAY = ["lloyd", "gain_random_label", "gain_seed_nearest", "gain_dsq_nearest"]
TABLE = ["lloyd", "lloyd_dsq", "minibatch", "online_lvq", "gain_random_label", "gain_seed_nearest_first", "bisect_lloyd", "bisect_lloyd_dsq", "gain_bisect_random_label", "cosine_bisect"]
CURVE = "method string, k int, run int, epoch int, distortion double, comparisons long, moves long, n long, seconds double"


def _runs(rows: DataFrame, settings: list[tuple[str, int, int]], refined: bool = False) -> DataFrame:
    """Every (method, k, run) as a task of its own over the same rows, which are broadcast after a size check."""
    n = rows.count()
    if n > LOCAL_ROWS:
        raise ValueError(f"{n} rows are too many for one task")
    spark = rows.sparkSession
    x = spark.sparkContext.broadcast(_matrix(rows.select("id", "vec").orderBy("id").toArrow()["vec"].combine_chunks()))
    grid = spark.createDataFrame(settings, "method string, k int, run int").repartition(len(settings))

    def each(frames):
        for f in frames:
            for method, k, run in f.itertuples(index=False):
                began = time.time()
                got = kernels.METHODS[method](x.value, int(k), 1000 + int(run))
                own = kernels.sse(x.value, got.labels, got.k) / len(x.value)
                history = got.history[:-1] + [got.history[-1] | {"distortion": own}]
                took = time.time() - began
                if refined:
                    better = kernels.gain_kway(x.value, int(k), got.labels, seed=1000 + int(run))
                    history = [history[-1] | {"epoch": 0}, better.history[-1] | {"epoch": 1}]
                out = pd.DataFrame(history)[["epoch", "distortion", "comparisons", "moves"]]
                yield out.assign(method=method, k=k, run=run, n=len(x.value), seconds=took)[[c.split()[0] for c in CURVE.split(", ")]]

    return grid.mapInPandas(each, CURVE)


def _on_both(spark: SparkSession, d: str, settings: list[tuple[str, int, int]]) -> DataFrame:
    """On the unit vectors and on those of unequal lengths."""
    sets = (("emb64", features.emb64), ("emb64_scaled", features.emb64_scaled))
    one, two = (_runs(f(spark, d), settings).withColumn("rows", F.lit(name)) for name, f in sets)
    return one.unionByName(two)


def w1(spark: SparkSession, d: str, k: int = 20) -> DataFrame:
    """Starts compared, epoch by epoch."""
    return _on_both(spark, d, [(m, k, 0) for m in KWAY])


def w2(spark: SparkSession, d: str, k: int = 20) -> DataFrame:
    """Best against first moves for the three starts."""
    return _on_both(spark, d, [(m, k, 0) for m in kernels.FLAT if m.startswith("gain")])


def w3(spark: SparkSession, d: str, k: int = 20) -> DataFrame:
    return _runs(features.emb64_scaled(spark, d), [(m, k, 0) for m in ("lloyd", "lloyd_dsq", "minibatch", "online_lvq", "gain_random_label")])


def w4(spark: SparkSession, d: str, k: int = 16, runs: int = 128) -> DataFrame:
    """Spread over runs: quartiles per method."""
    every = _runs(features.emb64_scaled(spark, d), [(m, k, r) for m in ("lloyd", "lloyd_dsq", "minibatch", "gain_random_label") for r in range(runs)])
    last = every.groupBy("method", "run").agg(F.max_by("distortion", "epoch").alias("distortion"))
    return metrics.run_summary(last)


def w5(spark: SparkSession, d: str, k: int = 20) -> DataFrame:
    """Hierarchies before (epoch 0) and after (epoch 1) refinement."""
    return _runs(features.emb64_scaled(spark, d), [(m, k, 0) for m in kernels.HIERARCHIES], refined=True)


def w5_line4(spark: SparkSession, d: str, k: int = 20, max_epochs: int = 3) -> DataFrame:
    """The same on the whole of line4 with the distributed engines, a few epochs of refinement."""
    rows, out = features.line4(spark, d).select("id", "vec"), []
    for name, run in SPLITS.items():
        got = run(rows, k)
        better = kway.refine(got, rows, max_epochs=max_epochs)
        out += [(name, e, float(r.history[-1]["distortion"]), int(sum(h["comparisons"] for h in r.history))) for e, r in ((0, got), (1, better))]
    return spark.createDataFrame(out, "method string, epoch int, distortion double, comparisons long")


def w6(spark: SparkSession, d: str, m: int = 8, codewords: int = 256, methods: list[str] | None = None, ranks: tuple[int, ...] = (1, 5, 10, 50, 100)) -> DataFrame:
    """Recall of coded nearest-neighbour search per clusterer; m = 8 or 16, flat or bisecting by `methods`.

    Queries are the ids that 10 divides; of the rest odd ones train the words, even ones are searched.
    """
    rows = features.emb64(spark, d)
    queries, rest = rows.where("id % 10 = 0"), rows.where("id % 10 <> 0")
    training, base = rest.where("id % 2 = 1"), rest.where("id % 2 = 0")
    truth, out = pq.exact_knn(queries, base, 1), None
    for method in methods or TABLE:
        books = pq.train_pq(training, m, 64, codewords, method)
        got = pq.adc_search(queries, pq.pq_encode(base, books, m, 64), books, m, max(ranks))
        part = pq.recall_at(got, truth, list(ranks)).select(F.lit(method).alias("method"), F.lit(m).alias("m"), "rank", "recall")
        out = part if out is None else out.unionByName(part)
    return out


def w10(spark: SparkSession, d: str, ks: tuple[int, ...] = (5, 10, 15, 20), corpora: int = 15, restarts: int = 10, methods: list[str] | None = None, cls: str = "lang", vocab: int = 512) -> DataFrame:
    """Mean over corpora of the best entropy of several runs, per method and k. cls: lang, source, or labels (the
    quality and toxicity of the labelled documents, the others left out)."""
    docs = load_table(spark, d, "documents")
    known = load_table(spark, d, "labels").select("doc_id", F.concat_ws("-", "quality", "toxic").alias("labels")) if cls == "labels" else docs
    vec = features.doc_terms(docs, vocab).join(known.select(F.col("doc_id").alias("id"), F.col(cls).alias("cls")), "id")
    names = sorted(methods or TABLE, key=lambda m: (m != "online_lvq", not m.startswith("gain")))  # what takes longest begins first
    # rows are written once, by corpus; every method reads them again as tasks of its own, however small the shuffle
    work = vec.withColumn("corpus", (F.col("id") % corpora).cast("int")).repartitionById(corpora, F.pmod("id", F.lit(corpora)).cast("int"))

    def each(method: str, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.zeros((len(pdf), vocab))
        x[np.repeat(np.arange(len(pdf)), pdf["slots"].map(len)), np.concatenate(pdf["slots"].to_numpy()).astype(np.int64)] = np.concatenate(pdf["weights"].to_numpy())
        corpus, (code, known) = int(pdf["corpus"].iloc[0]), pd.factorize(pdf["cls"])
        best = dict.fromkeys(ks, np.inf)
        for k, _, labels in kernels.labels_of(method, x, sorted({min(k, len(x)) for k in ks}), list(range(restarts))):
            h = entropy(labels, code, len(known))
            best |= {asked: min(best[asked], h) for asked in ks if min(asked, len(x)) == k}
        return pd.DataFrame({"method": method, "corpus": corpus, "k": list(best), "entropy": list(best.values())})

    def by(method: str) -> DataFrame:
        def corpus(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            if got := [f for f in frames if len(f)]:
                for _, part in pd.concat(got).sort_values("id").groupby("corpus"):
                    yield each(method, part)

        return work.mapInPandas(corpus, "method string, corpus int, k int, entropy double")

    per = reduce(DataFrame.unionAll, map(by, names))
    return per.groupBy("method", "k").agg(F.avg("entropy").alias("entropy"))


def entropy(labels: np.ndarray, code: np.ndarray, classes: int) -> float:
    """Entropy of the class codes (-1: none) within clusters, weighted by size, 1 where all classes are alike."""
    t = np.bincount(labels * (classes + 1) + code + 1, minlength=(labels.max() + 1) * (classes + 1)).reshape(-1, classes + 1)
    t = t[t.sum(1) > 0]
    p = t / t.sum(1, keepdims=True)
    h = -(p * np.log(np.where(p > 0, p, 1))).sum(1) / np.log(max(classes, 2))
    return float((t.sum(1) * h).sum() / t.sum())


#: Distributed runs by name: rows, k -> result.
SPLITS = {"gain_bisect_random_label": lambda r, k: kway.gain_bisect(r, k, max_epochs=5, local_rows=100_000), "bisect_lloyd": lambda r, k: kway.gain_split(r, k, splitter="lloyd", init="seed_nearest", max_epochs=5, local_rows=100_000)}
ENGINES = {
    "gain_random_label": lambda r, k: kway.gain_kway(r, k, max_epochs=3),
    "gain_seed_nearest_first": lambda r, k: kway.gain_kway(r, k, "seed_nearest", "first", max_epochs=3),
    "lloyd": lambda r, k: kway.lloyd(r, k, max_epochs=3),
    "minibatch": lambda r, k: kway.minibatch(r, k, iterations=3),
} | SPLITS
GROWTH = "method string, n long, k int, distortion double, comparisons long, seconds double, rows_a_second double"


def _timed(rows: DataFrame, k: int, methods: list[str] | None) -> list[tuple]:
    """Time, comparisons and distortion of the distributed engines over whole rows; three epochs of flat methods."""
    n, out = rows.count(), []
    for name in methods or ENGINES:
        began = time.time()
        got = ENGINES[name](rows, k)
        got.assignments.agg(F.count(F.lit(1))).first()
        took = time.time() - began
        value = got.history[-1].get("distortion")
        if value is None:
            value = state.objectives(got.state(rows)).first().distortion
        out.append((name, n, k, float(value), int(sum(h["comparisons"] for h in got.history)), took, n / took))
    return out


def w11(spark: SparkSession, d: str, k: int = 32, shares: tuple[int, ...] = (100, 10, 1), methods: list[str] | None = None) -> DataFrame:
    """Over n: a hundredth, a tenth and the whole of line4."""
    rows = features.line4(spark, d).select("id", "vec")
    out = []
    for share in shares:
        out += _timed(rows.where(F.pmod(F.xxhash64("id"), F.lit(share)) == 0), k, methods)
    return spark.createDataFrame(out, GROWTH)


def w12(spark: SparkSession, d: str, ks: tuple[int, ...] = (8, 16, 32, 64), methods: list[str] | None = None) -> DataFrame:
    """Over k, on the whole of line4."""
    rows = features.line4(spark, d).select("id", "vec")
    out = []
    for k in ks:
        out += _timed(rows, k, methods or ["gain_random_label", "lloyd", "minibatch", "gain_bisect_random_label"])
    return spark.createDataFrame(out, GROWTH)


def w15(spark: SparkSession, d: str, k: int = 16) -> DataFrame:
    """Comparisons of one pass over every split node, measured and nominal, of s-way splitting."""
    rows = features.part2(spark, d).select("id", "vec")
    n, out = rows.count(), []
    for s in (2, 3, 4, 8, k):
        got = kway.gain_split(rows, k, s)
        below: dict[str, int] = {}
        for x in got.nodes:
            below[x["parent"]] = below.get(x["parent"], 0) + 1
        measured = sum(x["cnt"] * (below[x["node_id"]] - 1) for x in got.nodes if not x["is_leaf"])
        out.append((s, float(measured), float(metrics.nominal_comparisons(n, k, s)), float(got.history[-1]["distortion"])))
    return spark.createDataFrame(out, "s int, measured double, nominal double, distortion double")


def w13(spark: SparkSession, d: str, k: int = 8) -> DataFrame:
    """Rows with a nearer centroid than their own, at the start and after so many epochs; 2-D."""
    x = _matrix(features.part2(spark, d).orderBy("id").toArrow()["vec"].combine_chunks())
    first = kernels.start(x, k, "random_label", np.random.default_rng(42))
    rows = [(0, violations(x, kernels.Run(first, k)), kernels.sse(x, first, k) / len(x))]
    for epochs in (1, 3, 10, 200):
        run = kernels.gain_kway(x, k, max_epochs=epochs)
        rows.append((epochs, violations(x, run), run.history[-1]["distortion"]))
    return spark.createDataFrame(rows, "epochs int, violations long, distortion double")


def w14(spark: SparkSession, d: str, k: int = 3) -> DataFrame:
    """Two splits break the nearest-centroid condition; refinement restores it."""
    x = _matrix(features.part2(spark, d).orderBy("id").toArrow()["vec"].combine_chunks())
    split = kernels.hierarchy(x, k)
    better = kernels.gain_kway(x, k, split.labels, max_epochs=200)
    return spark.createDataFrame([(n, violations(x, r), kernels.sse(x, r.labels, k) / len(x)) for n, r in (("split", split), ("refined", better))], "state string, violations long, distortion double")


def violations(x: np.ndarray, run: kernels.Run) -> int:
    c = run.centroids(x)
    d2 = ((x[:, None, :] - c[None]) ** 2).sum(2)
    return int((d2.min(1) < d2[np.arange(len(x)), run.labels] - 1e-9).sum())


def w16(spark: SparkSession, d: str, k: int = 64) -> DataFrame:
    """Candidate pruning: comparisons and distortion per k0, by row and by cluster; k0 = k is without."""
    x = _matrix(features.emb64_scaled(spark, d).orderBy("id").toArrow()["vec"].combine_chunks())
    shared = spark.sparkContext.broadcast(x)
    grid = [(mode, k0) for mode in kernels.CANDIDATES for k0 in (2, 4, 8, 16)] + [("none", k)]

    def each(frames):
        for f in frames:
            out = []
            for mode, k0 in f.itertuples(index=False):
                run = kernels.gain_kway(shared.value, k, candidates=None if mode == "none" else k0, candidate_mode="row" if mode == "none" else mode, max_epochs=20)
                out.append((mode, k0, sum(h["comparisons"] for h in run.history), run.history[-1]["distortion"]))
            yield pd.DataFrame(out, columns=["mode", "k0", "comparisons", "distortion"])

    return spark.createDataFrame(grid, "mode string, k0 int").repartition(len(grid)).mapInPandas(each, "mode string, k0 int, comparisons long, distortion double")


def order_vlad(spark: SparkSession, d: str, words: int = 16, keep: int = 16, sample_rows: int = 2000) -> DataFrame:
    """Rows of an order pooled to one unit vector: vocabulary, residual sums, signed root, principal axes.

    The vocabulary is trained on the sample_rows rows of least hash; every row is pooled.
    """
    rows = features.line4(spark, d)
    sample = _matrix(rows.orderBy(F.xxhash64("id")).limit(sample_rows).toArrow()["vec"].combine_chunks())
    c = kernels.gain_kway(sample, words).centroids(sample)
    pooled = metrics.vlad_pool(rows, c).select("id", root_normalize(F.col("vec")).alias("vec"))
    mean, axes = metrics.pca_fit(pooled, words * 4, keep)
    return metrics.pca_apply(pooled, mean, axes).select("id", unit(F.col("vec")).alias("vec"))


def w17(spark: SparkSession, d: str, k: int = 16, methods: list[str] | None = None) -> DataFrame:
    return _runs(order_vlad(spark, d), [(m, k, 0) for m in methods or TABLE]).groupBy("method", "n", "k").agg(F.max_by("distortion", "epoch").alias("distortion"), F.sum("comparisons").alias("comparisons"))


def given(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    """Tables as (id, vec, cluster) with the partition that the formulas are checked on."""
    doubles = F.transform("vec", lambda x: x.cast("double")).alias("vec")
    sets = {"emb64": (features.emb64, "label"), "emb64_scaled": (features.emb64_scaled, "label"), "part2": (features.part2, "label"), "acct1": (features.acct1, "label"), "line4": (features.line4, "l_returnflag")}
    out = {name: f(spark, d).select("id", doubles, F.col(label).cast("string").alias("cluster")) for name, (f, label) in sets.items()}
    for name, f in (("user7", features.user7), ("cust4", features.cust4)):
        out[name] = f(spark, d).select("id", doubles, (F.col("id") % 5).cast("string").alias("cluster"))
    return out


def w18(spark: SparkSession, d: str) -> DataFrame:
    """The move conditions on the embeddings by label: pairs on which the exact form and the gain disagree (beyond
    rounding), the share on which the large-cluster form does, and rows that could move or have a nearer centroid."""
    rows = given(spark, d)["emb64"].withColumn("cluster", F.col("cluster").cast("int"))
    s = state.cluster_state(rows)
    g = state.gains(rows, s)
    one = lambda c: F.sum(F.when(c, 1).otherwise(0))
    pairs = g.agg(one((F.abs("gain") > 1e-9) & (F.col("exact") != (F.col("gain") > 0))).alias("unequal"), F.avg((F.col("exact") != F.col("approx")).cast("double")).alias("approx_differs"), F.count_distinct(F.when((F.col("gain") > 1e-9) & (F.col("cnt_u") > 1), F.col("id"))).alias("improving"))
    pairs = pairs.withColumn("approx_differs", F.round("approx_differs", 9))
    return pairs.crossJoin(state.lloyd_violations(rows, s).agg(F.count(F.lit(1)).alias("violations")))


#: Places to round to; the squares of sums of prices go to 10^16.
DIGITS = {"cust4": -5}


def w19(spark: SparkSession, d: str) -> DataFrame:
    """The objectives of every table by its given partition, with the squared errors summed row by row beside the closed form."""
    out = None
    for name, rows in given(spark, d).items():
        s = state.cluster_state(rows)
        columns = [F.round(c, DIGITS.get(name, 3)).alias(c) for c in ("total", "score", "sse", "sse_by_row", "distortion", "pair_exact", "pair_approx")]
        part = state.objectives(s).crossJoin(state.sse_brute(rows, s).withColumnRenamed("sse", "sse_by_row")).select(F.lit(name).alias("rows"), "n", *columns, F.round("pair_gap", 6).alias("pair_gap"))
        out = part if out is None else out.unionByName(part)
    return out
