"""Fixed-point sums beyond a long, all pairs in tiles, comparisons counted from a table."""

import random

from pyspark.sql import functions as F

from gainclust import registry
from gainclust.functions.vectors import to_fixed
from gainclust.operators import kway
from gainclust.operators import state as st
from gainclust.streaming import streams

BIG = [(i, [2e4 + i % 5 + 1000 * (i % 2), float(i % 3)], i % 4 // 2) for i in range(40)]


def big(spark):
    return spark.createDataFrame(BIG, "id long, vec array<double>, cluster int").withColumn("vec", to_fixed(F.col("vec")))


def test_state_beyond_a_long(spark):
    rows = big(spark)
    got = {r.cluster: r for r in st.cluster_state(rows, fixed=True).collect()}
    pairs = {r.cluster: r.pair_sum for r in st.pair_measures(st.cluster_state(rows, fixed=True)).collect()}
    for c in (0, 1):
        mine = [[int(x * 10_000) for x in v] for _, v, label in BIG if label == c]
        s = [sum(x) for x in zip(*mine)]
        dd, xx = sum(x * x for x in s), sum(x * x for v in mine for x in v)
        assert dd > 1 << 63 and (got[c].cnt, got[c].sum_vec, int(got[c].dd), int(got[c].xx)) == (len(mine), s, dd, xx)
        assert int(pairs[c]) == len(mine) * xx - dd


def test_moves_beyond_a_long(spark):
    rows = big(spark)
    state = st.cluster_state(rows, fixed=True)
    assert st.gains(rows, state, fixed=True).count() == 40
    half = {i: i % 2 for i in range(40)}
    assert kway.relational_epoch(rows, 2, 2, 1, 42, 4, fixed=True).count() == 40
    odd = rows.select("id", "vec", (F.col("id") % 2).cast("int").alias("cluster"))
    s = st.cluster_state(odd, fixed=True)
    assert {r.id: r.cluster for r in st.assign_nearest(rows, s, True).collect()} == half
    assert {r.id: r.cluster for r in streams.score_stream(rows, s).collect()} == half
    assert {r.id: r.cluster for r in st.row_candidates(rows, s, 1, True).collect()} == half
    assert st.lloyd_violations(odd, s, True).isEmpty()
    assert st.padded(s, 3, 2, fixed=True).where("cluster = 2").first().dd == 0


def test_closed_pair_sum_of_any_size(spark, tmp_path):
    for name, price, kind in (("small", 20.0, "bigint"), ("large", 5e6, "decimal(38,0)")):
        d = str(tmp_path / name)
        spark.range(64).select(F.col("id").alias("p_partkey"), F.lit(8).alias("p_size"), (price * (1 + F.col("id") % 2)).alias("p_retailprice")).write.parquet(f"{d}/part.parquet")
        out = registry.pair_sum_closed(spark, d)
        assert dict(out.dtypes)["pair_sum"] == kind
        assert int(out.first().pair_sum) == 32 * 32 * int(price * 100) ** 2
        assert registry.objectives_part(spark, d).first().n == 64


def test_all_pairs_in_tiles(spark):
    rng = random.Random(5)
    data = [(i // 2 if 40 <= i < 60 else i, [rng.randrange(-9, 9) * (10**8 if i % 3 == 2 else 1), rng.randrange(3)], i % 3) for i in range(90)]
    data += [(200, [1, None], 0), (201, None, 1), (None, [1, 2], 1), (202, [7, 7], None), (203, [1, 1], 5), (204, [4, 4], 6), (205, [4, 4], 6), (206, [1, None], 7), (207, [1, 1], 7)]
    want = {}
    for a, (i, x, c) in enumerate(data):
        for j, y, e in data[:a]:
            if c is not None and c == e and i is not None and j is not None and i != j:
                whole = x and y and None not in x + y
                want[c] = want.get(c) if not whole else (want.get(c) or 0) + sum((p - q) ** 2 for p, q in zip(x, y))
    rows = spark.createDataFrame(data, "id long, vec array<long>, cluster int")
    assert want[2] > 1 << 63 and want[6] == 0 and want[7] is None
    for tile in (4, 4096):
        assert {r.cluster: r.pair_sum if r.pair_sum is None else int(r.pair_sum) for r in st.pair_sum_bruteforce(rows, tile).collect()} == want


def test_nominal_comparisons_of_a_table(spark, tmp_path):
    rows = [(1.0, 2.0, 0.1, 0.1)] * 11 + [(1.0, None, 0.1, 0.1)]
    spark.createDataFrame(rows, "l_quantity double, l_extendedprice double, l_discount double, l_tax double").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert {r.s: r.comparisons for r in registry.nominal_comparisons(spark, str(tmp_path)).collect()} == {2: 44, 4: 66, 16: 165}
