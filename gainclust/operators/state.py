"""Cluster state (count, sum vector, squared norms) and the objectives that follow from it.

With c the sum vector's squared norm ``dd``, the rows' squared norms ``xx`` and the count ``cnt`` of a cluster:
SSE = sum(xx - dd / cnt); the score that can grow is G = sum(dd / cnt), and SSE + G is constant.
"""

from __future__ import annotations

from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainclust.functions.vectors import dot, norm2, sub

#: A state is sent to every executor; larger ones are refused.
MAX_STATE_BYTES = 512 << 20

#: Squared sums and sums of squares in fixed point: some 10,000 rows of a cluster are enough to pass the end of a long.
WIDE = "decimal(38,0)"


def cluster_state(rows: DataFrame, fixed: bool = False) -> DataFrame:
    """From (id, vec, cluster): (cluster, cnt, sum_vec, dd, xx). Sums combine before the shuffle; no Python.

    In fixed point dd and xx are decimals of 38 digits, exact at any size.
    """
    kind, wide = ("long", WIDE) if fixed else ("double", "double")
    long_form = rows.select("cluster", F.posexplode("vec").alias("pos", "x")).groupBy("cluster", "pos").agg(F.sum(F.col("x").cast(kind)).alias("s"))
    sums = long_form.groupBy("cluster").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "s"))), lambda p: p["s"]).alias("sum_vec"))
    scalars = rows.groupBy("cluster").agg(F.count(F.lit(1)).alias("cnt"), F.sum(norm2(F.col("vec"), kind).cast("decimal(20,0)" if fixed else kind)).cast(wide).alias("xx"))
    return scalars.join(sums, "cluster").select("cluster", "cnt", "sum_vec", norm2(F.col("sum_vec"), wide).alias("dd"), "xx")


def centroids(state: DataFrame) -> DataFrame:
    return state.select("cluster", F.transform("sum_vec", lambda x: x / F.col("cnt")).alias("centroid"))


def pair_measures(state: DataFrame) -> DataFrame:
    """Per cluster: pair_inner, pair_sum (of squared distances) and mean_pair (null for a single row)."""
    pairs = F.col("cnt") * F.col("xx") - F.col("dd")
    return state.select("cluster", ((F.col("dd") - F.col("xx")).cast("double") / F.lit(2)).alias("pair_inner"), pairs.alias("pair_sum"), F.when(F.col("cnt") > 1, (2 * pairs).cast("double") / (F.col("cnt") * (F.col("cnt") - 1)).cast("double")).alias("mean_pair"))


def pair_sum_bruteforce(rows: DataFrame, tile: int = 4096) -> DataFrame:
    """Reference only, in fixed point: all pairs (ids a < b) of each cluster, pair_sum a decimal.

    Different vectors meet once, in tiles, and count as often as their copies do; copies are at distance zero.
    """
    rows = rows.where("cluster IS NOT NULL AND id IS NOT NULL").select("cluster", "id", F.col("vec").cast("array<long>").alias("vec"), F.size("vec").alias("d"))
    whole = rows.where("vec IS NOT NULL AND forall(vec, x -> x IS NOT NULL)")
    few = whole.groupBy("cluster", "d", "vec").agg(F.count(F.lit(1)).alias("n"))
    most = few.groupBy("cluster", "d").count().agg(F.max("count")).first()[0] or 1
    tiles = -(-most // tile)
    placed = few.withColumn("t", F.pmod(F.xxhash64("vec"), F.lit(tiles)).cast("int")).withColumn("u", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))))
    placed = placed.select("cluster", "d", "t", "vec", "n", F.least("t", "u").alias("a"), F.greatest("t", "u").alias("b"))

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        one = pdf["t"] == pdf["a"].iloc[0]
        other = one if pdf["a"].iloc[0] == pdf["b"].iloc[0] else ~one
        total = _pair_tiles(pdf[one], pdf[other]) if pdf["d"].iloc[0] and one.any() and other.any() else 0
        return pd.DataFrame({"cluster": [pdf["cluster"].iloc[0]], "d": [pdf["d"].iloc[0]], "sum": [Decimal(total // 2 if other is one else total)]})

    kind = rows.schema["cluster"].dataType.simpleString()
    met = placed.groupBy("cluster", "d", "a", "b").applyInPandas(meet, f"cluster {kind}, d int, sum {WIDE}").groupBy("cluster", "d").agg(F.sum("sum").alias("sum"))
    # rows that share an id are no pair
    shared = whole.join(whole.groupBy("cluster", "d", "id").count().where("count > 1").drop("count"), ["cluster", "d", "id"], "left_semi")
    x, y = shared.alias("x"), shared.alias("y")
    gap = norm2(sub(F.col("x.vec"), F.col("y.vec")), "long").cast(WIDE)
    same = x.join(y, (F.col("x.cluster") == F.col("y.cluster")) & (F.col("x.d") == F.col("y.d")) & (F.col("x.id") == F.col("y.id")))
    less = same.groupBy(F.col("x.cluster").alias("cluster"), F.col("x.d").alias("d")).agg((F.sum(gap) / 2).cast(WIDE).alias("less"))
    pairs = whole.groupBy("cluster", "d").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high")
    sums = pairs.join(met, ["cluster", "d"]).join(less, ["cluster", "d"], "left").groupBy("cluster").agg(F.sum(F.col("sum") - F.coalesce("less", F.lit(0))).alias("pair_sum"))
    every = rows.groupBy("cluster").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high").select("cluster")
    return every.join(sums, "cluster", "left").select("cluster", F.col("pair_sum").cast(WIDE).alias("pair_sum"))


def _pair_tiles(a: pd.DataFrame, b: pd.DataFrame, block: int = 256) -> int:
    """Squared distances of all rows of a to all of b, each as often as both rows' copies pair up."""
    x, y = np.stack(a["vec"].to_numpy()), np.stack(b["vec"].to_numpy())
    m, n = a["n"].to_numpy(), b["n"].to_numpy()
    most = sum((int(max(p, q)) - int(min(r, s))) ** 2 for p, q, r, s in zip(x.max(0), y.max(0), x.min(0), y.min(0)))
    if most * int(n.sum()) >= 1 << 63:
        x, y, n = x.astype(object), y.astype(object), n.astype(object)
    total = 0
    for i in range(0, len(x), block):
        d2 = 0
        for c in range(x.shape[1]):
            gap = x[i : i + block, c, None] - y[None, :, c]
            d2 = d2 + gap * gap
        total += sum(int(r) * int(w) for r, w in zip(d2 @ n, m[i : i + block]))
    return total


def objectives(state: DataFrame) -> DataFrame:
    """One row: n, total (constant), score, sse, distortion, the pair objective exact and approximate, and their gap."""
    dd, xx, cnt = (F.col(c).cast("double") for c in ("dd", "xx", "cnt"))
    agg = state.agg(
        F.sum("cnt").alias("n"), F.sum("xx").cast("double").alias("total"), F.sum(dd / cnt).alias("score"), F.sum(xx - dd / cnt).alias("sse"),
        F.sum(F.when(F.col("cnt") > 1, 2 * cnt / (cnt - 1) * (xx - dd / cnt)).otherwise(0.0)).alias("pair_exact"),
    )
    agg = agg.withColumn("distortion", F.col("sse") / F.col("n")).withColumn("pair_approx", 2 * F.col("total") - 2 * F.col("score"))
    return agg.withColumn("pair_gap", F.when(F.col("pair_exact") != 0, (F.col("pair_exact") - F.col("pair_approx")) / F.col("pair_exact")))


def sse_brute(rows: DataFrame, state: DataFrame) -> DataFrame:
    """Squared errors row by row against the centroids (broadcast: k rows)."""
    c = centroids(state)
    gap = F.aggregate(F.zip_with("vec", "centroid", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    return rows.join(F.broadcast(c), "cluster").agg(F.sum(gap).alias("sse"))


def size_report(state: DataFrame, k: int) -> DataFrame:
    return state.agg(F.min("cnt").alias("least"), F.max("cnt").alias("most"), (F.lit(k) - F.count(F.lit(1))).alias("empties"), F.stddev_pop("cnt").alias("spread"))


def padded(state: DataFrame, k: int, d: int, fixed: bool = False) -> DataFrame:
    """State with a zero row for every empty cluster of 0..k-1."""
    spark = state.sparkSession
    if k * d * 8 > MAX_STATE_BYTES:
        raise ValueError(f"{k} clusters of {d} components are too many to broadcast; use a hierarchy or candidates")
    zero = F.array_repeat(F.lit(0).cast("long" if fixed else "double"), d)
    ids = spark.range(k).select(F.col("id").cast("int").alias("cluster"))
    kind = WIDE if fixed else "double"
    return ids.join(state, "cluster", "left").select("cluster", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"), F.coalesce("sum_vec", zero).alias("sum_vec"), F.coalesce("dd", F.lit(0)).cast(kind).alias("dd"), F.coalesce("xx", F.lit(0)).cast(kind).alias("xx"))


def gains(rows: DataFrame, state: DataFrame, fixed: bool = False, parts: int | None = None) -> DataFrame:
    """For every row and every other cluster (with parts: of its node, clusters numbered node * parts + part):
    (id, u, v, gain, by_distance, exact, approx).

    gain splits into what v wins and what u loses; by_distance is the same through centroid distances; exact is
    the move condition by appendix averages, approx the form for large clusters.
    """
    kind = "long" if fixed else "double"
    one = lambda p: state.select(*[F.col(c).alias(f"{c}_{p}") for c in ("cluster", "cnt", "sum_vec")], F.col("dd").cast("double").alias(f"dd_{p}"))
    x = rows.select("id", "vec", F.col("cluster").alias("u"), norm2(F.col("vec"), kind).alias("q"))
    x = x.join(F.broadcast(one("u")), F.col("u") == F.col("cluster_u")).withColumn("p_u", dot(F.col("vec"), F.col("sum_vec_u"), kind)).drop("sum_vec_u", "cluster_u")
    other = F.col("u") != F.col("cluster_v")
    if parts:
        other &= F.floor(F.col("u") / parts) == F.floor(F.col("cluster_v") / parts)
    x = x.join(F.broadcast(one("v")), other).withColumn("p_v", dot(F.col("vec"), F.col("sum_vec_v"), kind)).drop("sum_vec_v", "vec")
    d = lambda c: F.col(c).cast("double")
    won = F.when(F.col("cnt_v") == 0, d("q")).otherwise(((2 * F.col("p_v") + F.col("q")).cast("double") - d("dd_v") / d("cnt_v")) / (d("cnt_v") + 1))
    lost = F.when(F.col("cnt_u") == 1, d("q")).otherwise(((2 * F.col("p_u") - F.col("q")).cast("double") - d("dd_u") / d("cnt_u")) / (d("cnt_u") - 1))
    far = lambda p: d("q") - 2 * d(f"p_{p}") / d(f"cnt_{p}") + d(f"dd_{p}") / (d(f"cnt_{p}") * d(f"cnt_{p}"))
    from_u = F.when(F.col("cnt_u") > 1, d("cnt_u") / (d("cnt_u") - 1) * far("u")).otherwise(0.0)
    to_v = F.when(F.col("cnt_v") > 0, d("cnt_v") / (d("cnt_v") + 1) * far("v")).otherwise(0.0)
    # averages of the two clusters without the row itself
    n_u, b_u = d("cnt_u") - 1, d("p_u") - d("q")
    a_u = d("dd_u") - 2 * d("p_u") + d("q")
    term = lambda n, b, a, factor: F.when(n > 0, 2 * factor(n) * b / n - a / (n * (n + 1)) + d("q") / (n + 1)).otherwise(d("q"))
    exact, large = (lambda n: n / (n + 1)), (lambda n: F.lit(1.0))
    side = lambda f: (term(n_u, b_u, a_u, f), term(d("cnt_v"), d("p_v"), d("dd_v"), f))
    (eu, ev), (au, av) = side(exact), side(large)
    return x.select("id", "u", F.col("cluster_v").alias("v"), (won - lost).alias("gain"), (from_u - to_v).alias("by_distance"), (eu < ev).alias("exact"), (au < av).alias("approx"), "cnt_u")


def best_moves(rows: DataFrame, state: DataFrame, fixed: bool = False, first: bool = False, least: float = 0.0, parts: int | None = None, near: DataFrame | None = None) -> DataFrame:
    """(id, u, v, gain) of each row that has an improving move: the best, ties to the lower cluster; or the first.

    near: the clusters to test, of a row (id, cluster) or of the cluster it is in (cluster, near).
    """
    g = gains(rows, state, fixed, parts).where((F.col("gain") > least) & (F.col("cnt_u") > 1))
    if near is not None and "id" in near.columns:
        g = g.join(near.select("id", F.col("cluster").alias("v")), ["id", "v"], "left_semi")
    elif near is not None:
        g = g.join(F.broadcast(near.select(F.col("cluster").alias("u"), F.col("near").alias("v"))), ["u", "v"], "left_semi")
    pick = F.max(F.struct((-F.col("v")).alias("neg"), "gain", "u")) if first else F.max(F.struct("gain", (-F.col("v")).alias("neg"), "u"))
    return g.groupBy("id").agg(pick.alias("m")).select("id", F.col("m.u").alias("u"), (-F.col("m.neg")).alias("v"), F.col("m.gain").alias("gain"))


def assign_nearest(rows: DataFrame, state: DataFrame, fixed: bool = False) -> DataFrame:
    """(id, cluster, dist2) of the nearest non-empty centroid, ties to the lower cluster; the state is broadcast."""
    kind = "long" if fixed else "double"
    c = state.where("cnt > 0").select(F.col("cluster").alias("c"), "cnt", "sum_vec", F.col("dd").cast("double").alias("dd"))
    d2 = norm2(F.col("vec"), kind).cast("double") - 2 * dot(F.col("vec"), F.col("sum_vec"), kind).cast("double") / F.col("cnt") + F.col("dd").cast("double") / (F.col("cnt").cast("double") * F.col("cnt"))
    near = rows.select("id", "vec").crossJoin(F.broadcast(c)).select("id", F.struct(d2.alias("d"), F.col("c")).alias("m")).groupBy("id").agg(F.min("m").alias("m"))
    return near.select("id", F.col("m.c").alias("cluster"), F.col("m.d").alias("dist2"))


def lloyd_violations(rows: DataFrame, state: DataFrame, fixed: bool = False) -> DataFrame:
    """Rows that have a strictly nearer centroid than their own."""
    c = state.where("cnt > 0").select(F.col("cluster").alias("cluster"), "cnt", "sum_vec", F.col("dd").cast("double").alias("dd"))
    near = assign_nearest(rows, state, fixed).select("id", F.col("cluster").alias("nearest"), "dist2")
    kind = "long" if fixed else "double"
    own = rows.join(F.broadcast(c), "cluster")
    d2 = norm2(F.col("vec"), kind).cast("double") - 2 * dot(F.col("vec"), F.col("sum_vec"), kind).cast("double") / F.col("cnt") + F.col("dd").cast("double") / (F.col("cnt").cast("double") * F.col("cnt"))
    return own.select("id", "cluster", d2.alias("own2")).join(near, "id").where("dist2 < own2").select("id", "cluster", "nearest")


def appendix_terms(rows: DataFrame, state: DataFrame, fixed: bool = False) -> DataFrame:
    """(id, cluster, mu, delta) for every row and cluster, the row left out of its own: mu is the cluster's squared sum
    over n (n + 1), delta the mean inner product with its rows; null for a cluster without other rows."""
    kind = "long" if fixed else "double"
    x = rows.select("id", "vec", F.col("cluster").alias("u"), norm2(F.col("vec"), kind).alias("q")).crossJoin(F.broadcast(state.select("cluster", "cnt", "sum_vec", "dd")))
    x = x.withColumn("p", dot(F.col("vec"), F.col("sum_vec"), kind))
    own = F.col("u") == F.col("cluster")
    n = F.when(own, F.col("cnt") - 1).otherwise(F.col("cnt")).cast("double")
    dd = F.when(own, F.col("dd") - 2 * F.col("p") + F.col("q")).otherwise(F.col("dd")).cast("double")
    p = F.when(own, F.col("p") - F.col("q")).otherwise(F.col("p")).cast("double")
    return x.select("id", "cluster", F.when(n > 0, dd / (n * (n + 1))).alias("mu"), F.when(n > 0, p / n).alias("delta"))


def row_candidates(rows: DataFrame, state: DataFrame, k0: int, fixed: bool = False) -> DataFrame:
    """(id, cluster, place): per row the k0 clusters it would win most in, ties to the lower; its own counts like any other.

    The state is one broadcast row, so nothing is shuffled and no pair leaves its row's task.
    """
    kind = "long" if fixed else "double"
    every = state.where("cnt > 0").agg(F.array_sort(F.collect_list(F.struct("cluster", "cnt", "sum_vec", F.col("dd").cast("double").alias("dd")))).alias("every"))
    q = norm2(F.col("vec"), kind)
    won = lambda s: ((2 * dot(F.col("vec"), s["sum_vec"], kind) + q).cast("double") - s["dd"].cast("double") / s["cnt"]) / (s["cnt"].cast("double") + 1)
    ranked = F.slice(F.array_sort(F.transform("every", lambda s: F.struct((-won(s)).alias("loss"), s["cluster"].alias("cluster")))), 1, k0)
    return rows.crossJoin(F.broadcast(every)).select("id", F.posexplode(ranked).alias("pos", "c")).select("id", "c.cluster", (F.col("pos") + 1).alias("place"))


def moved(before: DataFrame, after: DataFrame) -> DataFrame:
    """(id, cluster) of the rows whose label is not what it was."""
    return after.select("id", "cluster").exceptAll(before.select("id", "cluster"))


def candidate_table(state: DataFrame, k0: int) -> DataFrame:
    """(cluster, near, place, dist2): the k0 nearest other centroids of each cluster."""
    c = centroids(state.where("cnt > 0"))
    a, b = c.alias("a"), c.alias("b")
    d2 = F.aggregate(F.zip_with("a.centroid", "b.centroid", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    pairs = a.join(F.broadcast(b), F.col("a.cluster") != F.col("b.cluster")).select(F.col("a.cluster").alias("cluster"), F.col("b.cluster").alias("near"), F.round(d2, 6).alias("dist2"))
    return pairs.withColumn("place", F.row_number().over(Window.partitionBy("cluster").orderBy("dist2", "near"))).where(F.col("place") <= k0)
