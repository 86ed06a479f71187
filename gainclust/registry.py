"""Queries of the clustering engine and their SQL equivalents.

Vectors enter the SQL checks in fixed point, so sums are exact in any order; published doubles are rounded to nine
places after division by the scale.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gainclust.functions.vectors import FIXED, portable_hash, root_normalize, to_fixed, unit
from gainclust.operators import external, kernels, kway, metrics, pq
from gainclust.operators import state as st
from gainclust.plans import workloads
from gainclust.sources import features
from gainclust.sources.storage import load_table, stored
from gainclust.streaming import streams

K, SEED, SHARE = 10, 42, 4
SQ = float(FIXED * FIXED)
QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def _emb(spark: SparkSession, d: str) -> DataFrame:
    return features.emb64(spark, d).select("id", to_fixed(F.col("vec")).alias("vec"), F.col("label").alias("cluster"))


def _part(spark: SparkSession, d: str) -> DataFrame:
    return features.part2(spark, d).select("id", to_fixed(F.col("vec")).alias("vec"), F.col("label").alias("cluster"))


def _state(rows: DataFrame) -> DataFrame:
    return st.cluster_state(rows, fixed=True)


def _bigint(few: DataFrame, name: str) -> DataFrame:
    """A decimal of a few rows as long; if one of them does not fit, all stay exact decimals."""
    few = stored(few, "wide")
    fits = few.agg(F.bool_and(F.col(name).try_cast("long").isNotNull() | F.col(name).isNull())).first()[0]
    return few if fits is False else few.withColumn(name, F.col(name).cast("long"))


def r9(c) -> F.Column:
    return F.round(c, 9)


_FX = "floor(({}) * 10000 + 0.5)::BIGINT"
_BASE = {
    "emb": f"x AS MATERIALIZED (SELECT vec_id AS id, label AS c, list_transform(embedding, lambda v: {_FX.format('v::DOUBLE')}) AS v FROM embeddings)",
    "emb_double": "x AS MATERIALIZED (SELECT vec_id AS id, label AS c, list_transform(embedding, lambda v: v::DOUBLE) AS v FROM embeddings)",
    "part": f"x AS MATERIALIZED (SELECT p_partkey AS id, p_size % 8 AS c, [{_FX.format('p_size::DOUBLE')}, {_FX.format('p_retailprice / 100')}] AS v FROM part)",
}


def _prefix(base: str, kind: str = "BIGINT") -> str:
    out = f"""WITH {_BASE[base]},
e AS MATERIALIZED (SELECT id, c, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
s AS MATERIALIZED (SELECT c, pos, sum(val)::BIGINT AS s FROM e GROUP BY c, pos),
q AS MATERIALIZED (SELECT id, sum(val * val)::BIGINT AS q FROM e GROUP BY id),
st AS MATERIALIZED (SELECT a.c, a.cnt, b.dd, d.xx FROM (SELECT c, count(*) AS cnt FROM x GROUP BY c) a JOIN (SELECT c, sum(s * s)::BIGINT AS dd FROM s GROUP BY c) b USING (c) JOIN (SELECT c, sum(val * val)::BIGINT AS xx FROM e GROUP BY c) d USING (c)),
p AS MATERIALIZED (SELECT e.id, e.c AS u, s.c AS v, sum(e.val * s.s)::BIGINT AS p FROM e JOIN s USING (pos) GROUP BY e.id, e.c, s.c),
g AS MATERIALIZED (SELECT pv.id, pv.u, pv.v,
    ((2 * pv.p + q.q)::DOUBLE - sv.dd::DOUBLE / sv.cnt::DOUBLE) / (sv.cnt::DOUBLE + 1) - CASE WHEN su.cnt = 1 THEN q.q::DOUBLE ELSE ((2 * pu.p - q.q)::DOUBLE - su.dd::DOUBLE / su.cnt::DOUBLE) / (su.cnt::DOUBLE - 1) END AS gain, su.cnt AS cnt_u
    FROM p pv JOIN p pu ON pu.id = pv.id AND pu.v = pv.u JOIN q ON q.id = pv.id JOIN st su ON su.c = pv.u JOIN st sv ON sv.c = pv.v WHERE pv.v <> pv.u),
n AS MATERIALIZED (SELECT p.id, p.u, p.v, q.q::DOUBLE - 2 * p.p::DOUBLE / st.cnt + st.dd::DOUBLE / (st.cnt::DOUBLE * st.cnt) AS d2 FROM p JOIN q USING (id) JOIN st ON st.c = p.v)
"""
    return out.replace("::BIGINT", f"::{kind}")


EMB, PART = _prefix("emb"), _prefix("part")


@query(EMB + "SELECT s.c AS cluster, st.cnt AS cnt, st.dd AS dd, st.xx AS xx, s.pos::INTEGER AS pos, s.s AS s FROM s JOIN st USING (c)")
def state_by_label(spark, d):
    return _state(_emb(spark, d)).select("cluster", "cnt", F.col("dd").cast("long").alias("dd"), F.col("xx").cast("long").alias("xx"), F.posexplode("sum_vec").alias("pos", "s"))


@query(EMB + "SELECT s.c AS cluster, s.pos::INTEGER AS pos, round(s.s / st.cnt::DOUBLE, 9) AS x FROM s JOIN st USING (c)")
def centroids_by_label(spark, d):
    return st.centroids(_state(_emb(spark, d))).select("cluster", F.posexplode("centroid").alias("pos", "x")).withColumn("x", r9(F.col("x")))


@query(EMB + "SELECT min(cnt) AS least, max(cnt) AS most, 12 - count(*) AS empties, round(stddev_pop(cnt), 9) AS spread FROM st")
def size_report(spark, d):
    return st.size_report(_state(_emb(spark, d)), 12).withColumn("spread", r9(F.col("spread")))


_OBJ = """, o AS (SELECT sum(cnt)::BIGINT AS n, sum(xx)::DOUBLE AS total, sum(dd::DOUBLE / cnt) AS score, sum(xx::DOUBLE - dd::DOUBLE / cnt) AS sse,
    sum(CASE WHEN cnt > 1 THEN 2 * cnt::DOUBLE / (cnt::DOUBLE - 1) * (xx::DOUBLE - dd::DOUBLE / cnt) ELSE 0 END) AS pe FROM st)
SELECT n, round(total / 1e8::DOUBLE, 6) AS total, round(score / 1e8::DOUBLE, 6) AS score, round(sse / 1e8::DOUBLE, 6) AS sse, round(sse / n / 1e8::DOUBLE, 6) AS distortion,
    round(pe / 1e8::DOUBLE, 6) AS pair_exact, round((2 * total - 2 * score) / 1e8::DOUBLE, 6) AS pair_approx, round((pe - (2 * total - 2 * score)) / pe, 9) AS pair_gap FROM o"""


def _objectives(rows: DataFrame) -> DataFrame:
    o = st.objectives(_state(rows))
    cols = ("total", "score", "sse", "distortion", "pair_exact", "pair_approx")
    return o.select("n", *[F.round(F.col(c) / SQ, 6).alias(c) for c in cols], r9(F.col("pair_gap")).alias("pair_gap"))


@query(EMB + _OBJ)
def objectives_emb(spark, d):
    return _objectives(_emb(spark, d))


@query(PART + _OBJ)
def objectives_part(spark, d):
    return _objectives(_part(spark, d))


@query(EMB + "SELECT round(sum(power(e.val - s.s::DOUBLE / st.cnt, 2)) / 1e8::DOUBLE, 6) AS sse FROM e JOIN s ON s.c = e.c AND s.pos = e.pos JOIN st ON st.c = e.c")
def sse_brute(spark, d):
    rows = _emb(spark, d)
    return st.sse_brute(rows, _state(rows)).select(F.round(F.col("sse") / SQ, 6).alias("sse"))


@query(EMB + "SELECT c AS cluster, (dd - xx) / 2.0::DOUBLE AS pair_inner, cnt * xx - dd AS pair_sum, CASE WHEN cnt > 1 THEN 2 * (cnt * xx - dd) / (cnt * (cnt - 1))::DOUBLE END AS mean_pair FROM st")
def pair_measures(spark, d):
    return st.pair_measures(_state(_emb(spark, d))).withColumn("pair_sum", F.col("pair_sum").cast("long"))


@query(PART + "SELECT a.c AS cluster, sum(power(a.v[1] - b.v[1], 2) + power(a.v[2] - b.v[2], 2))::BIGINT AS pair_sum FROM x a JOIN x b ON a.c = b.c AND a.id < b.id GROUP BY a.c")
def pair_sum_bruteforce(spark, d):
    return _bigint(st.pair_sum_bruteforce(_part(spark, d)), "pair_sum")


@query(PART + "SELECT c AS cluster, cnt * xx - dd AS pair_sum FROM st")
def pair_sum_closed(spark, d):
    return _bigint(st.pair_measures(_state(_part(spark, d))).select("cluster", "pair_sum"), "pair_sum")


def _gains(rows: DataFrame) -> DataFrame:
    return st.gains(rows, _state(rows), fixed=True)


@query(EMB + "SELECT id, u, v, round(gain / 1e8::DOUBLE, 9) AS gain FROM g")
def gain_all_pairs(spark, d):
    return _gains(_emb(spark, d)).select("id", "u", "v", r9(F.col("gain") / SQ).alias("gain"))


@query(EMB + "SELECT id, u, v, round(gain / 1e8::DOUBLE, 9) AS gain FROM g")
def gain_by_distance(spark, d):
    return _gains(_emb(spark, d)).select("id", "u", "v", r9(F.col("by_distance") / SQ).alias("gain"))


@query(PART + "SELECT id, u, v, gain > 0 AS moves FROM g WHERE abs(gain) > 1")
def move_condition_exact(spark, d):
    return _gains(_part(spark, d)).where(F.abs("gain") > 1).select("id", "u", "v", F.col("exact").alias("moves"))


_SIDE = "CASE WHEN {n} > 0 THEN 2 * {b} / {n} - {a} / ({n} * ({n} + 1)) + q / ({n} + 1) ELSE q END"
_APPROX = f""", z AS (SELECT pv.id, pv.v, q.q::DOUBLE AS q, su.cnt::DOUBLE - 1 AS nu, pu.p::DOUBLE - q.q AS bu, su.dd::DOUBLE - 2 * pu.p::DOUBLE + q.q AS au, sv.cnt::DOUBLE AS nv, pv.p::DOUBLE AS bv, sv.dd::DOUBLE AS av
    FROM p pv JOIN p pu ON pu.id = pv.id AND pu.v = pv.u JOIN q ON q.id = pv.id JOIN st su ON su.c = pv.u JOIN st sv ON sv.c = pv.v WHERE pv.v <> pv.u),
y AS (SELECT id, v, {_SIDE.format(n='nu', b='bu * nu / (nu + 1)', a='au')} < {_SIDE.format(n='nv', b='bv * nv / (nv + 1)', a='av')} AS exact, {_SIDE.format(n='nu', b='bu', a='au')} < {_SIDE.format(n='nv', b='bv', a='av')} AS approx FROM z)"""


@query(PART + _APPROX + " SELECT round(avg((exact <> approx)::INTEGER), 9) AS disagree FROM y")
def move_condition_approx(spark, d):
    """How often the large-cluster form decides otherwise."""
    return _gains(_part(spark, d)).agg(r9(F.avg(F.when(F.col("exact") != F.col("approx"), 1.0).otherwise(0.0))).alias("disagree"))


_MOVE = "SELECT id, u, v, round(gain / 1e8::DOUBLE, 9) AS gain FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY {}) AS r FROM g WHERE gain > 0 AND cnt_u > 1) WHERE r = 1"


def _moves(rows: DataFrame, first: bool) -> DataFrame:
    return st.best_moves(rows, _state(rows), True, first).select("id", "u", "v", r9(F.col("gain") / SQ).alias("gain"))


@query(EMB + _MOVE.format("gain DESC, v"))
def best_move(spark, d):
    return _moves(_emb(spark, d), False)


@query(EMB + _MOVE.format("v"))
def first_move(spark, d):
    return _moves(_emb(spark, d), True)


@query(PART + "SELECT count(DISTINCT id) AS improving, count(*) AS pairs FROM g WHERE gain > 0 AND cnt_u > 1")
def improving_moves(spark, d):
    return _gains(_part(spark, d)).where("gain > 0 AND cnt_u > 1").agg(F.count_distinct("id").alias("improving"), F.count(F.lit(1)).alias("pairs"))


_NEAR = "(SELECT id, u, v, d2 FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY d2, v) AS r FROM n) WHERE r = 1)"


@query(EMB + f"SELECT id, v AS cluster, round(d2 / 1e8::DOUBLE, 9) AS dist2 FROM {_NEAR}")
def assign_nearest(spark, d):
    rows = _emb(spark, d)
    return st.assign_nearest(rows, _state(rows), True).select("id", "cluster", r9(F.col("dist2") / SQ).alias("dist2"))


@query(PART + f"SELECT a.id, a.u AS cluster, a.v AS nearest FROM {_NEAR} a JOIN n b ON b.id = a.id AND b.v = a.u WHERE a.d2 < b.d2")
def lloyd_violations(spark, d):
    rows = _part(spark, d)
    return st.lloyd_violations(rows, _state(rows), True)


@query(EMB + """, cc AS (SELECT s.c, s.pos, s.s / st.cnt::DOUBLE AS x FROM s JOIN st USING (c)),
pr AS (SELECT a.c AS cluster, b.c AS near, round(sum(power(a.x - b.x, 2)), 6) AS dist2 FROM cc a JOIN cc b ON a.pos = b.pos AND a.c <> b.c GROUP BY a.c, b.c),
rk AS (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY dist2, near)::INTEGER AS place FROM pr) SELECT cluster, near, place FROM rk WHERE place <= 4""")
def candidate_table(spark, d):
    return st.candidate_table(_state(_emb(spark, d)), 4).select("cluster", "near", "place")


_HASH = "('0x' || substr(md5({} || ':{}'), 1, 7))::BIGINT"


@query(f"SELECT vec_id AS id, ({_HASH.format('vec_id', SEED)} % {K})::INTEGER AS cluster FROM embeddings")
def init_random_label(spark, d):
    return kway.random_labels(features.emb64(spark, d).select("id"), K, SEED)


def _seeded(rows: DataFrame, k: int) -> DataFrame:
    """State of k clusters of one row each: the rows of least hash."""
    order = Window.orderBy(portable_hash(F.col("id"), f"seed{SEED}"), "id")
    top = rows.orderBy(portable_hash(F.col("id"), f"seed{SEED}"), "id").limit(k)
    return _state(top.withColumn("cluster", (F.row_number().over(order) - 1).cast("int")))


_SEEDS = f"""WITH {{base}},
e AS MATERIALIZED (SELECT id, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
q AS MATERIALIZED (SELECT id, sum(val * val)::BIGINT AS q FROM e GROUP BY id),
l0 AS MATERIALIZED (SELECT id, nth AS c FROM (SELECT id, (row_number() OVER (ORDER BY {_HASH.format('id', f'seed{SEED}')}, id) - 1)::INTEGER AS nth FROM x) WHERE nth < {{k}}),
"""


def _lloyd_step(i: int) -> str:
    return f"""s{i} AS MATERIALIZED (SELECT c, pos, sum(val)::BIGINT AS s FROM e JOIN l{i} USING (id) GROUP BY c, pos),
t{i} AS MATERIALIZED (SELECT a.c, a.cnt, b.dd FROM (SELECT c, count(*) AS cnt FROM l{i} GROUP BY c) a JOIN (SELECT c, sum(s * s)::BIGINT AS dd FROM s{i} GROUP BY c) b USING (c)),
p{i} AS MATERIALIZED (SELECT e.id, s.c, sum(e.val * s.s)::BIGINT AS p FROM e JOIN s{i} s USING (pos) GROUP BY e.id, s.c),
l{i + 1} AS MATERIALIZED (SELECT id, c FROM (SELECT p.id, p.c, row_number() OVER (PARTITION BY p.id ORDER BY q.q::DOUBLE - 2 * p.p::DOUBLE / t.cnt + t.dd::DOUBLE / (t.cnt::DOUBLE * t.cnt), p.c) AS r FROM p{i} p JOIN q USING (id) JOIN t{i} t USING (c)) WHERE r = 1)"""


def lloyd_relational(rows: DataFrame, k: int, epochs: int) -> DataFrame:
    """The classic loop by joins and aggregates only, from hash-chosen seeds: (id, cluster)."""
    state, labels = _seeded(rows, k), None
    for _ in range(epochs):
        labels = st.assign_nearest(rows, state, True).select("id", "cluster")
        state = _state(rows.select("id", "vec").join(labels, "id"))
    return labels


@query(_SEEDS.format(base=_BASE["emb"], k=K) + _lloyd_step(0) + " SELECT id, c AS cluster FROM l1")
def init_seed_nearest(spark, d):
    return lloyd_relational(_emb(spark, d), K, 1)


@query(_SEEDS.format(base=_BASE["part"], k=6) + ", ".join(_lloyd_step(i) for i in range(3)) + " SELECT id, c AS cluster FROM l3")
def lloyd_e3(spark, d):
    return lloyd_relational(_part(spark, d), 6, 3)


def _gain_step(i: int, k: int, first: bool = False, epoch: int | None = None, share: int = SHARE, near: str = "") -> str:
    """Labels l{i+1} from l{i}: one round of proposals; near: a join that leaves only the clusters to test."""
    pick = "v" if first else "gain DESC, v"
    return f"""s{i} AS MATERIALIZED (SELECT c, pos, sum(val)::BIGINT AS s FROM e JOIN l{i} USING (id) GROUP BY c, pos),
t{i} AS MATERIALIZED (SELECT r.c, coalesce(a.cnt, 0) AS cnt, coalesce(b.dd, 0) AS dd FROM (SELECT range::INTEGER AS c FROM range({k})) r LEFT JOIN (SELECT c, count(*) AS cnt FROM l{i} GROUP BY c) a USING (c) LEFT JOIN (SELECT c, sum(s * s)::BIGINT AS dd FROM s{i} GROUP BY c) b USING (c)),
p{i} AS MATERIALIZED (SELECT e.id, s.c, sum(e.val * s.s)::BIGINT AS p FROM e JOIN l{i} USING (id) JOIN s{i} s USING (pos) GROUP BY e.id, s.c),
g{i} AS MATERIALIZED (SELECT l.id, tv.c AS v, CASE WHEN tv.cnt = 0 THEN q.q::DOUBLE ELSE ((2 * pv.p + q.q)::DOUBLE - tv.dd::DOUBLE / tv.cnt::DOUBLE) / (tv.cnt::DOUBLE + 1) END
    - ((2 * pu.p - q.q)::DOUBLE - tu.dd::DOUBLE / tu.cnt::DOUBLE) / (tu.cnt::DOUBLE - 1) AS gain
    FROM l{i} l JOIN q USING (id) JOIN t{i} tu ON tu.c = l.c AND tu.cnt > 1 JOIN p{i} pu ON pu.id = l.id AND pu.c = l.c JOIN t{i} tv ON tv.c <> l.c {near} LEFT JOIN p{i} pv ON pv.id = l.id AND pv.c = tv.c),
m{i} AS MATERIALIZED (SELECT id, v FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY {pick}) AS r FROM g{i} WHERE gain > 0) WHERE r = 1),
l{i + 1} AS MATERIALIZED (SELECT l.id, CASE WHEN m.v IS NOT NULL AND {_HASH.format('l.id', f'{SEED}-{epoch or i + 1}')} % {share} = 0 THEN m.v ELSE l.c END AS c FROM l{i} l LEFT JOIN m{i} m USING (id))"""


_ROWS = """e AS MATERIALIZED (SELECT id, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
q AS MATERIALIZED (SELECT id, sum(val * val)::BIGINT AS q FROM e GROUP BY id),
"""


def _gain_chain(base: str, k: int, epochs: int, first: bool = False) -> str:
    return f"WITH {_BASE[base]},\n{_ROWS}l0 AS MATERIALIZED (SELECT id, ({_HASH.format('id', SEED)} % {k})::INTEGER AS c FROM x),\n" + ", ".join(_gain_step(i, k, first) for i in range(epochs)) + f" SELECT id, c AS cluster FROM l{epochs}"


def _doubles(rows: DataFrame) -> DataFrame:
    return rows.withColumn("vec", F.transform("vec", lambda x: x.cast("double") / FIXED))


def _relational(rows: DataFrame, k: int, epochs: int, move: str = "best", init="random_label", **options) -> DataFrame:
    return kway.gain_kway(_doubles(rows), k, init, move, engine="relational", max_epochs=epochs, seed=SEED, share=SHARE, fixed=True, **options).assignments


@query(_gain_chain("emb", K, 1))
def gain_kway_e1(spark, d):
    return _relational(_emb(spark, d), K, 1)


@query(_gain_chain("emb", K, 3))
def gain_kway_e3(spark, d):
    return _relational(_emb(spark, d), K, 3)


@query(_gain_chain("part", 6, 3))
def gain_kway_part_e3(spark, d):
    return _relational(_part(spark, d), 6, 3)


@query(_gain_chain("emb", K, 2, True))
def gain_kway_first_e2(spark, d):
    return _relational(_emb(spark, d), K, 2, "first")


@query(_SEEDS.format(base=_BASE["part"], k=6) + _lloyd_step(0) + ", " + ", ".join(_gain_step(i, 6, epoch=i) for i in (1, 2)) + " SELECT id, c AS cluster FROM l3")
def gain_kway_seeded_e2(spark, d):
    return _relational(_part(spark, d), 6, 2, init="seed_nearest")


def _near_rows(i: int, k0: int) -> str:
    return f"""w{i} AS MATERIALIZED (SELECT id, c FROM (SELECT p.id, p.c, row_number() OVER (PARTITION BY p.id ORDER BY ((2 * p.p + q.q)::DOUBLE - t.dd::DOUBLE / t.cnt) / (t.cnt::DOUBLE + 1) DESC, p.c) AS r FROM p{i} p JOIN q USING (id) JOIN t{i} t ON t.c = p.c) WHERE r <= {k0})"""


def _near_clusters(i: int, k0: int) -> str:
    return f"""cc{i} AS (SELECT s.c, s.pos, s.s / t.cnt::DOUBLE AS x FROM s{i} s JOIN t{i} t USING (c)),
w{i} AS MATERIALIZED (SELECT u, v FROM (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY d2, v) AS r FROM (SELECT a.c AS u, b.c AS v, round(sum(power(a.x - b.x, 2)), 6) AS d2 FROM cc{i} a JOIN cc{i} b ON a.pos = b.pos AND a.c <> b.c GROUP BY a.c, b.c)) WHERE r <= {k0})"""


def _candidate_chain(base: str, k: int, k0: int, mode: str) -> str:
    """Three epochs, the first with all clusters."""
    out = f"WITH {_BASE[base]},\n{_ROWS}l0 AS MATERIALIZED (SELECT id, ({_HASH.format('id', SEED)} % {k})::INTEGER AS c FROM x),\n" + _gain_step(0, k)
    for i in (1, 2):
        near = "JOIN w1 w ON w.id = l.id AND w.c = tv.c" if mode == "row" else f"JOIN w{i} w ON w.u = l.c AND w.v = tv.c"
        step = _gain_step(i, k, near=near)
        if mode == "cluster" or i == 1:
            made = _near_rows(i, k0) if mode == "row" else _near_clusters(i, k0)
            step = step.replace(f"\ng{i} AS", f"\n{made},\ng{i} AS")
        out += ", " + step
    return out + " SELECT id, c AS cluster FROM l3"


@query(_candidate_chain("part", 8, 3, "row"))
def gain_kway_row_candidates_e3(spark, d):
    return _relational(_part(spark, d), 8, 3, candidates=3, warm_epochs=1)


@query(_candidate_chain("part", 8, 3, "cluster"))
def gain_kway_cluster_candidates_e3(spark, d):
    return _relational(_part(spark, d), 8, 3, candidates=3, warm_epochs=1, candidate_mode="cluster")


# --- hierarchies: SQL splits one leaf after the other, the engine all that may be wanted at once


def _tree_sql(base: str, s: int, k: int, priority: str, epochs: int = 2, share: int = 2) -> tuple[str, int]:
    """Nodes n{steps} (id, node) after all splits; b{t} is the leaf of split t with its rows."""
    steps = (k - 1) // (s - 1)
    out = f"WITH {_BASE[base]},\n{_ROWS}n0 AS MATERIALIZED (SELECT id, '0' AS node FROM x)"
    for t in range(steps):
        key = "count(*)"
        if priority == "avg_pair":
            out += f""", a{t} AS (SELECT node, count(DISTINCT id) AS cnt, sum(val * val)::DOUBLE AS xx FROM n{t} JOIN e USING (id) GROUP BY node),
d{t} AS (SELECT node, sum(s * s)::DOUBLE AS dd FROM (SELECT node, pos, sum(val)::BIGINT AS s FROM n{t} JOIN e USING (id) GROUP BY node, pos) GROUP BY node)"""
            choose = f"SELECT node, cnt FROM a{t} JOIN d{t} USING (node) WHERE cnt > 1 ORDER BY 2 * (xx - dd / cnt) / (cnt - 1) DESC, node LIMIT 1"
        else:
            choose = f"SELECT node, {key} AS cnt FROM n{t} GROUP BY node HAVING count(*) > 1 ORDER BY cnt DESC, node LIMIT 1"
        i = 10 * (t + 1)
        first = _HASH.format("(node || ':' || id)", SEED)
        out += f""", b{t} AS MATERIALIZED ({choose}),
l{i} AS MATERIALIZED (SELECT id, ({first} % {s})::INTEGER AS c FROM n{t} JOIN b{t} USING (node)),
""" + ", ".join(_gain_step(i + j, s, epoch=j + 1, share=share) for j in range(epochs))
        out += f", n{t + 1} AS MATERIALIZED (SELECT n.id, CASE WHEN l.c IS NULL THEN n.node ELSE n.node || '.' || l.c END AS node FROM n{t} n LEFT JOIN l{i + epochs} l USING (id))"
    return out, steps


def _leaves_sql(base: str, s: int, k: int, priority: str = "size") -> str:
    out, steps = _tree_sql(base, s, k, priority)
    return out + f", l0 AS MATERIALIZED (SELECT id, (dense_rank() OVER (ORDER BY node) - 1)::INTEGER AS c FROM n{steps})"


def _tree(spark, d, k: int, s: int = 2, priority: str = "size") -> kway.ClusterResult:
    return kway.gain_split(_doubles(_part(spark, d)), k, s, priority=priority, engine="relational", max_epochs=2, share=2, seed=SEED, fixed=True)


@query(_leaves_sql("part", 2, 4) + " SELECT id, c AS cluster FROM l0")
def gain_bisect_k4(spark, d):
    return _tree(spark, d, 4).assignments


@query(_leaves_sql("part", 2, 9) + " SELECT id, c AS cluster FROM l0")
def gain_bisect_k9(spark, d):
    return _tree(spark, d, 9).assignments


@query(_leaves_sql("part", 3, 7) + " SELECT id, c AS cluster FROM l0")
def gain_split_s3(spark, d):
    return _tree(spark, d, 7, 3).assignments


@query(_leaves_sql("part", 2, 6, "avg_pair") + " SELECT id, c AS cluster FROM l0")
def gain_bisect_avg_pair(spark, d):
    return _tree(spark, d, 6, priority="avg_pair").assignments


@query(_leaves_sql("part", 2, 4) + ", " + ", ".join(_gain_step(i, 4) for i in range(2)) + " SELECT id, c AS cluster FROM l2")
def refine_k4(spark, d):
    return _relational(_part(spark, d), 4, 2, init=_tree(spark, d, 4).assignments)


def _visited_sql(base: str, k: int) -> str:
    out, steps = _tree_sql(base, 2, k, "size")
    return out + " SELECT sum(cnt)::BIGINT AS visited FROM (" + " UNION ALL ".join(f"SELECT cnt FROM b{t}" for t in range(steps)) + ")"


@query(_visited_sql("part", 9))
def visited(spark, d):
    """Rows in split nodes, which one pass over each of them visits."""
    nodes = [(bool(x["is_leaf"]), int(x["cnt"])) for x in _tree(spark, d, 9).nodes]
    return metrics.visited(spark.createDataFrame(nodes, "is_leaf boolean, cnt long"))


def _minibatch_sql(base: str, k: int, iterations: int, fraction: float) -> str:
    out = _SEEDS.format(base=_BASE[base], k=k) + """s0 AS MATERIALIZED (SELECT l0.c, e.pos, e.val AS s FROM l0 JOIN e USING (id)), t0 AS MATERIALIZED (SELECT c, 1 AS cnt, sum(s * s)::BIGINT AS dd FROM s0 GROUP BY c)"""
    near = lambda i, name, rows: f"""p{i} AS MATERIALIZED (SELECT e.id, s.c, sum(e.val * s.s)::BIGINT AS p FROM e JOIN s{i} s USING (pos) {rows} GROUP BY e.id, s.c),
{name} AS MATERIALIZED (SELECT id, c FROM (SELECT p.id, p.c, row_number() OVER (PARTITION BY p.id ORDER BY q.q::DOUBLE - 2 * p.p::DOUBLE / t.cnt + t.dd::DOUBLE / (t.cnt::DOUBLE * t.cnt), p.c) AS r FROM p{i} p JOIN q USING (id) JOIN t{i} t USING (c)) WHERE r = 1)"""  # noqa: E731
    for i in range(iterations):
        batch = f"WHERE {_HASH.format('e.id', f'mb{SEED}-{i}')} < {int(fraction * (1 << 28))}"
        every = " UNION ALL ".join(f"SELECT id, c FROM a{j}" for j in range(i + 1))
        out += f""", {near(i, f'a{i}', batch)},
w{i} AS MATERIALIZED ({every}),
s{i + 1} AS MATERIALIZED (SELECT c, pos, sum(val)::BIGINT AS s FROM w{i} JOIN e USING (id) GROUP BY c, pos UNION ALL SELECT c, pos, s FROM s0 WHERE c NOT IN (SELECT c FROM w{i})),
t{i + 1} AS MATERIALIZED (SELECT c, coalesce(any_value(n), 1) AS cnt, sum(s * s)::BIGINT AS dd FROM s{i + 1} LEFT JOIN (SELECT c, count(*) AS n FROM w{i} GROUP BY c) USING (c) GROUP BY c)"""
    return out + ", " + near(iterations, "z", "") + " SELECT id, c AS cluster FROM z"


@query(_minibatch_sql("part", 6, 3, 0.1))
def minibatch_e3(spark, d):
    return kway.minibatch_relational(_part(spark, d), 6, 0.1, 3, SEED)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Three epochs of gain clustering of the embeddings: (cluster, cnt, sse)."""
    labels = gain_kway_e3(spark, d)
    rows = _emb(spark, d).select("id", "vec").join(labels, "id")
    return _state(rows).select("cluster", "cnt", F.round((F.col("xx").cast("double") - F.col("dd").cast("double") / F.col("cnt")) / SQ, 6).alias("sse"))


# --- distributed and sequential runs: results depend on layout or on random states, so properties are returned


def _summary(name: str, rows: DataFrame, got: kway.ClusterResult) -> DataFrame:
    s = got.state(rows)
    return st.objectives(s).select(F.lit(name).alias("method"), "n", F.lit(got.k).alias("k"), "distortion").crossJoin(st.size_report(s, got.k))


def _method(name: str, run):
    def f(spark, d):
        rows = features.emb64_scaled(spark, d).select("id", "vec")
        return _summary(name, rows, run(rows))

    f.__name__ = name
    return query()(f)


_method("gain_kway_partitioned", lambda r: kway.gain_kway(r, K, engine="partitioned", max_epochs=5))
_method("gain_kway_partitioned_candidates", lambda r: kway.gain_kway(r, K, engine="partitioned", max_epochs=5, candidates=4))
_method("gain_kway_partitioned_seeded", lambda r: kway.gain_kway(r, K, "seed_nearest", engine="partitioned", max_epochs=3))
_method("gain_kway_partitioned_dsq_first", lambda r: kway.gain_kway(r, K, "dsq_nearest", "first", engine="partitioned", max_epochs=3))
_method("gain_kway_sequential", lambda r: kway.gain_kway(r, K, engine="sequential"))
_method("gain_bisect_k10", lambda r: kway.gain_bisect(r, K))
_method("gain_bisect_distributed", lambda r: kway.gain_bisect(r, 4, local_rows=200))
_method("gain_bisect_avg_pair_tasks", lambda r: kway.gain_split(r, K, priority="avg_pair"))
_method("gain_split_s3_tasks", lambda r: kway.gain_split(r, K, s=3))
_method("gain_kway_partitioned_cluster_candidates", lambda r: kway.gain_kway(r, K, max_epochs=5, candidates=4, candidate_mode="cluster"))
_method("gain_kway_partitioned_waves", lambda r: kway.gain_kway(r, K, max_epochs=3, waves=4))
_method("refine_bisect", lambda r: kway.refine(kway.gain_bisect(r, K), r))
_method("lloyd_distributed", lambda r: kway.lloyd(r, K, max_epochs=5))
_method("lloyd_dsq_distributed", lambda r: kway.lloyd(r, K, "dsq", max_epochs=5))
_method("minibatch_distributed", lambda r: kway.minibatch(r, K, iterations=5))
_method("online_lvq", lambda r: kway.local(r, lambda x, _: kernels.online_lvq(x, K), k=K))
_method("bisect_lloyd", lambda r: kway.gain_split(r, K, splitter="lloyd", init="seed_nearest"))
_method("bisect_lloyd_dsq", lambda r: kway.gain_split(r, K, splitter="lloyd", init="dsq_nearest"))
_method("cosine_bisect", lambda r: kway.cosine_bisect(r, K))


# --- documents


_TERMS = "WITH tc AS (SELECT doc_id AS id, term, count(*) AS tf FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS term FROM documents) GROUP BY doc_id, term),\ndf AS (SELECT term, count(*) AS df, ln((SELECT count(*) FROM documents)::DOUBLE / count(*)) AS idf FROM tc GROUP BY term)\n"


@query(_TERMS + "SELECT id, term, tf FROM tc")
def term_counts(spark, d):
    return features.term_counts(load_table(spark, d, "documents"))


@query(_TERMS + "SELECT term, df, round(idf, 9) AS idf FROM df")
def idf(spark, d):
    docs = load_table(spark, d, "documents")
    return features.idf(features.term_counts(docs), docs.count()).withColumn("idf", r9(F.col("idf")))


@query(_TERMS + ", top AS (SELECT * FROM df ORDER BY df DESC, term LIMIT 512), w AS (SELECT id, term, tf * idf AS w FROM tc JOIN top USING (term)) SELECT id, term, round(CASE WHEN sqrt(sum(w * w) OVER (PARTITION BY id)) > 0 THEN w / sqrt(sum(w * w) OVER (PARTITION BY id)) ELSE 0 END, 9) AS weight FROM w")
def tfidf(spark, d):
    return features.tfidf(load_table(spark, d, "documents"), 512).select("id", "term", r9(F.col("weight")).alias("weight"))


def _entropy_sql(classes: str) -> str:
    return f"""WITH a AS (SELECT doc_id AS id, ({_HASH.format('doc_id', 7)} % 8)::INTEGER AS cluster FROM documents), k AS ({classes}),
t AS (SELECT cluster, cls, count(*) AS n FROM a JOIN k USING (id) WHERE cls IS NOT NULL GROUP BY cluster, cls),
h AS (SELECT cluster, n, n::DOUBLE / sum(n) OVER (PARTITION BY cluster) AS p FROM t)
SELECT cluster, sum(n)::BIGINT AS cnt, round(-sum(p * ln(p)) / ln((SELECT count(DISTINCT cls) FROM k WHERE cls IS NOT NULL)), 9) AS entropy FROM h GROUP BY cluster"""


def _entropy(spark, d, classes: DataFrame) -> DataFrame:
    a = load_table(spark, d, "documents").select(F.col("doc_id").alias("id"), (portable_hash(F.col("doc_id"), 7) % 8).cast("int").alias("cluster"))
    return metrics.entropy(a, classes).withColumn("entropy", r9(F.col("entropy")))


@query(_entropy_sql("SELECT doc_id AS id, lang AS cls FROM documents"))
def entropy_lang(spark, d):
    return _entropy(spark, d, load_table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("cls")))


@query(_entropy_sql("SELECT doc_id AS id, source AS cls FROM documents"))
def entropy_source(spark, d):
    return _entropy(spark, d, load_table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("source").alias("cls")))


@query(_entropy_sql("SELECT doc_id AS id, quality || '-' || toxic AS cls FROM labels"))
def entropy_quality(spark, d):
    return _entropy(spark, d, load_table(spark, d, "labels").select(F.col("doc_id").alias("id"), F.concat_ws("-", "quality", "toxic").alias("cls")))


# --- product quantization


@query("WITH " + _BASE["emb"] + ", t AS (SELECT id, v, unnest(range(8))::INTEGER AS sub FROM x), y AS (SELECT id, sub, v[sub * 8 + 1 : sub * 8 + 8] AS w FROM t) SELECT id, sub, (generate_subscripts(w, 1) - 1)::INTEGER AS pos, unnest(w) AS x FROM y")
def pq_split(spark, d):
    return pq.split_subvectors(_emb(spark, d), 8, 64).select("id", "sub", F.posexplode("vec").alias("pos", "x"))


def _chosen_books(rows: DataFrame) -> DataFrame:
    return pq.split_subvectors(rows.where("id < 16"), 8, 64).select("sub", F.col("id").cast("int").alias("code"), "vec")


@query("WITH " + _BASE["emb"] + """, e AS (SELECT id, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
z AS (SELECT a.id, (a.pos // 8)::INTEGER AS sub, b.id::INTEGER AS code, sum((a.val - b.val) * (a.val - b.val))::BIGINT AS err2 FROM e a JOIN e b ON a.pos = b.pos AND b.id < 16 GROUP BY ALL)
SELECT id, sub, code, err2 FROM (SELECT *, row_number() OVER (PARTITION BY id, sub ORDER BY err2, code) AS r FROM z) WHERE r = 1""")
def pq_encode(spark, d):
    rows = _emb(spark, d)
    return pq.encode_relational(rows, _chosen_books(rows), 8, 64)


@query("WITH " + _BASE["emb"] + """, e AS (SELECT id, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
z AS (SELECT a.id AS query_id, b.id, sum((a.val - b.val) * (a.val - b.val))::BIGINT AS dist2 FROM e a JOIN e b ON a.pos = b.pos AND a.id % 10 = 0 AND b.id % 10 <> 0 GROUP BY ALL)
SELECT * FROM (SELECT query_id, id, dist2, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id)::INTEGER AS rank FROM z) WHERE rank <= 10""")
def exact_knn(spark, d):
    rows = _emb(spark, d)
    return pq.exact_knn_relational(rows.where("id % 10 = 0"), rows.where("id % 10 <> 0"), 10)


@query()
def adc_recall(spark, d):
    return workloads.w6(spark, d, methods=["gain_random_label"])


_WORDS = 256
_CODED = "WITH " + _BASE["emb"] + f""", e AS MATERIALIZED (SELECT id, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
z AS MATERIALIZED (SELECT a.id, (a.pos // 8)::INTEGER AS sub, b.id AS code, sum((a.val - b.val) * (a.val - b.val))::BIGINT AS err2 FROM e a JOIN e b ON a.pos = b.pos AND b.id < {_WORDS} GROUP BY ALL),
c AS MATERIALIZED (SELECT id, sub, code, err2 FROM (SELECT *, row_number() OVER (PARTITION BY id, sub ORDER BY err2, code) AS r FROM z) WHERE r = 1)"""


def _coded(spark, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows in fixed point as doubles, the books of chosen words, and the codes."""
    rows = _emb(spark, d)
    books = pq.split_subvectors(rows.where(f"id < {_WORDS}"), 8, 64).select("sub", F.col("id").cast("int").alias("code"), F.transform("vec", lambda x: x.cast("double")).alias("vec"))
    rows = rows.select("id", F.transform("vec", lambda x: x.cast("double")).alias("vec"))
    return rows, books, pq.pq_encode(rows, books, 8, 64)


_RANKED = "SELECT query_id, id, dist2, rank FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id)::INTEGER AS rank FROM f) WHERE rank <= 10"


@query(_CODED + ", f AS (SELECT q.id AS query_id, b.id, sum(q.err2)::DOUBLE AS dist2 FROM z q JOIN c b ON b.sub = q.sub AND b.code = q.code WHERE q.id % 10 = 0 AND b.id % 10 <> 0 GROUP BY ALL) " + _RANKED)
def adc_search(spark, d):
    """Queries as they are, the base coded."""
    rows, books, codes = _coded(spark, d)
    return pq.adc_search(rows.where("id % 10 = 0"), codes.where("id % 10 <> 0"), books, 8, 10)


@query(_CODED + """, f AS (SELECT q.id AS query_id, b.id, sum(z.err2)::DOUBLE AS dist2 FROM c q JOIN c b ON b.sub = q.sub JOIN z ON z.id = q.code AND z.sub = q.sub AND z.code = b.code WHERE q.id % 10 = 0 AND b.id % 10 <> 0 GROUP BY ALL) """ + _RANKED)
def sdc_search(spark, d):
    """Queries and base coded."""
    rows, books, codes = _coded(spark, d)
    return pq.adc_search(rows.where("id % 10 = 0"), codes.where("id % 10 <> 0"), books, 8, 10, symmetric=True)


@query(_CODED + " SELECT round(sum(err2) / count(DISTINCT id) / 1e8::DOUBLE, 9) AS mean_error FROM c")
def pq_error(spark, d):
    rows, books, codes = _coded(spark, d)
    return pq.pq_error(rows, pq.pq_decode(codes, books, 8)).select(r9(F.col("mean_error") / SQ).alias("mean_error"))


@query()
def train_pq(spark, d):
    return pq.train_pq(features.emb64(spark, d), 8, 64)


# --- vectors, pooling, features, measures


@query("WITH e AS (SELECT vec_id AS id, unnest(embedding)::DOUBLE * (1 + vec_id % 5) AS x, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) SELECT id, pos::INTEGER AS pos, round(x / sqrt(sum(x * x) OVER (PARTITION BY id)), 9) AS x FROM e")
def unit_vectors(spark, d):
    return features.emb64_scaled(spark, d).select("id", F.posexplode(unit(F.col("vec"))).alias("pos", "x")).withColumn("x", r9(F.col("x")))


@query("WITH e AS (SELECT vec_id AS id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) SELECT id, pos::INTEGER AS pos, round(sign(x) * sqrt(abs(x) / sum(abs(x)) OVER (PARTITION BY id)), 9) AS x FROM e")
def root_vectors(spark, d):
    return features.emb64(spark, d).select("id", F.posexplode(root_normalize(F.col("vec"))).alias("pos", "x")).withColumn("x", r9(F.col("x")))


WORDS = np.array([[10.0, 20.0, 5.0, 4.0], [25.0, 35.0, 5.0, 4.0], [40.0, 60.0, 5.0, 4.0]])


@query("""WITH l AS (SELECT l_orderkey AS id, row_number() OVER () AS r, [l_quantity, l_extendedprice / 1000, l_discount * 100, l_tax * 100] AS v FROM lineitem),
w AS (SELECT * FROM (VALUES (0, [10.0::DOUBLE, 20, 5, 4]), (1, [25.0::DOUBLE, 35, 5, 4]), (2, [40.0::DOUBLE, 60, 5, 4])) t(word, c)),
m AS (SELECT r, any_value(id) AS id, any_value(v) AS v, min((list_sum(list_transform(list_zip(v, c), lambda z: (z[1] - z[2]) * (z[1] - z[2]))), word)) AS b FROM l, w GROUP BY r),
y AS (SELECT m.id, w.word, unnest(list_transform(list_zip(m.v, w.c), lambda z: z[1] - z[2])) AS x, unnest(range(4)) AS pos FROM m JOIN w ON w.word = m.b[2]),
s AS (SELECT id, word * 4 + pos AS pos, sum(x) AS x FROM y GROUP BY ALL)
SELECT o.id, o.pos::INTEGER AS pos, round(coalesce(s.x, 0), 6) + 0.0 AS x FROM (SELECT id, unnest(range(12)) AS pos FROM (SELECT DISTINCT id FROM l)) o LEFT JOIN s ON s.id = o.id AND s.pos = o.pos""")
def vlad_pool(spark, d):
    return metrics.vlad_pool(features.line4(spark, d), WORDS).select("id", F.posexplode("vec").alias("pos", "x")).select("id", "pos", (F.round("x", 6) + F.lit(0.0)).alias("x"))


@query("WITH e AS (SELECT vec_id AS id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) SELECT a.pos::INTEGER AS i, b.pos::INTEGER AS j, round(avg(a.x), 9) AS mean, round(avg(a.x * b.x), 9) AS g FROM e a JOIN e b USING (id) GROUP BY ALL")
def pca_gram(spark, d):
    """What the axes are taken from."""
    return metrics.gram(features.emb64(spark, d)).select("i", F.posexplode("g").alias("j", "g"), "mean").select("i", "j", r9(F.col("mean")).alias("mean"), r9(F.col("g")).alias("g"))


def _exploded(rows: DataFrame) -> DataFrame:
    return rows.select("id", F.posexplode("vec").alias("pos", "x")).withColumn("x", F.round("x", 6))


@query("WITH u AS (SELECT user_id AS id, [count(*) FILTER (event_type = 'click')::DOUBLE, count(*) FILTER (event_type = 'purchase'), count(*) FILTER (event_type = 'error'), count(*) FILTER (event_type = 'signup'), count(*) FILTER (event_type = 'view'), avg(value), max(value)] AS v FROM events GROUP BY user_id) SELECT id, (generate_subscripts(v, 1) - 1)::INTEGER AS pos, round(unnest(v), 6) AS x FROM u")
def user7(spark, d):
    return _exploded(features.user7(spark, d))


@query("WITH u AS (SELECT o_custkey AS id, [count(*)::DOUBLE, sum(o_totalprice), avg(o_totalprice), max(o_totalprice)] AS v FROM orders GROUP BY o_custkey) SELECT id, (generate_subscripts(v, 1) - 1)::INTEGER AS pos, round(unnest(v), 6) AS x FROM u")
def cust4(spark, d):
    return _exploded(features.cust4(spark, d))


@query("SELECT user_id, time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'signup') AS signup, count(*) FILTER (event_type = 'view') AS \"view\", max(value) AS top FROM events GROUP BY ALL")
def user_windows(spark, d):
    return streams.user_windows(load_table(spark, d, "events"))


@query("WITH a AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM a) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS n FROM s GROUP BY user_id, g")
def user_sessions(spark, d):
    return streams.user_sessions(load_table(spark, d, "events"))


@query(PART + """SELECT id, v AS cluster FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY d2 , v) AS r FROM n) WHERE r = 1""")
def stream_score(spark, d):
    """The scoring expression on a batch; the tests run it on a stream."""
    rows = _part(spark, d)
    return streams.score_stream(rows, _state(rows))


_LINE4 = " AND ".join(f"l_{c} IS NOT NULL" for c in ("quantity", "extendedprice", "discount", "tax"))


@query(f"SELECT s::INTEGER AS s, round(n * (s - 1) * ln(16) / ln(s), 6) AS comparisons FROM (SELECT count(*) AS n FROM lineitem WHERE {_LINE4}), (VALUES (2), (4), (16)) t(s)")
def nominal_comparisons(spark, d):
    """Of splitting the rows of line4 with a whole vector into 16 leaves."""
    n = load_table(spark, d, "lineitem").where(_LINE4).agg(F.count(F.lit(1)).alias("n"))
    each = [F.struct(F.lit(s).alias("s"), F.round(metrics.nominal_comparisons(F.col("n"), 16, s), 6).alias("comparisons")) for s in (2, 4, 16)]
    return n.select(F.inline(F.array(*each)))


@query(_gain_chain("part", 6, 2).replace(" SELECT id, c AS cluster FROM l2", """, ct AS (SELECT a.c AS a, b.c AS b, count(*)::DOUBLE AS n FROM l1 a JOIN l2 b USING (id) GROUP BY ALL),
z AS (SELECT (SELECT sum(n * (n - 1) / 2) FROM ct) AS s, (SELECT sum(n) * (sum(n) - 1) / 2 FROM ct) AS every, (SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM ct GROUP BY a)) AS sa, (SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM ct GROUP BY b)) AS sb)
SELECT round((s - sa * sb / every) / ((sa + sb) / 2 - sa * sb / every), 9) AS rand FROM z"""))
def pair_agreement(spark, d):
    """Of the labels after one and after two epochs."""
    rows = _part(spark, d)
    return metrics.pair_agreement(_relational(rows, 6, 1), _relational(rows, 6, 2)).select(r9(F.col("rand")).alias("rand"))


@query()
def order_vlad(spark, d):
    return workloads.order_vlad(spark, d)

# --- seeds by squared distance, appendix averages, candidates, changes of labels


def _race_sql(base: str, k: int) -> str:
    """Seeds z{k} (c, id, v): the row of least hash, then k - 1 exponential races by squared distance."""
    gap = "list_sum(list_transform(list_zip(x.v, z.v), lambda w: (w[1] - w[2]) * (w[1] - w[2])))::DOUBLE"
    parts = [f"z1 AS MATERIALIZED (SELECT 0 AS c, id, v FROM x ORDER BY {_HASH.format('id', f'seed{SEED}')}, id LIMIT 1)"]
    for i in range(1, k):
        u = f"({_HASH.format('x.id', f'race{SEED}-{i}')} + 1)::DOUBLE / 268435456"
        parts.append(f"r{i} AS MATERIALIZED (SELECT x.id, any_value(x.v) AS v, min({gap}) AS d2 FROM x, z{i} z GROUP BY x.id)")
        parts.append(f"z{i + 1} AS MATERIALIZED (SELECT * FROM z{i} UNION ALL (SELECT {i}, x.id, x.v FROM r{i} x WHERE d2 > 0 ORDER BY -ln({u}) / d2, x.id LIMIT 1))")
    return f"WITH {_BASE[base]}, " + ", ".join(parts)


_DSQ = _race_sql("part", 4) + """, l0 AS MATERIALIZED (SELECT id, c FROM z4),
e AS MATERIALIZED (SELECT id, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
q AS MATERIALIZED (SELECT id, sum(val * val)::BIGINT AS q FROM e GROUP BY id), """


def _dsq_state(rows: DataFrame, k: int) -> DataFrame:
    """State of k clusters of one row each, the seeds of the race (k vectors)."""
    found = kway.seeds(rows, k, "dsq", SEED)
    seeds = rows.sparkSession.createDataFrame([(i, v, i) for i, v in enumerate(found)], "id long, vec array<long>, cluster int")
    return _state(seeds)


def _lloyd_dsq(rows: DataFrame, k: int, epochs: int) -> DataFrame:
    state, labels = _dsq_state(rows, k), None
    for _ in range(epochs):
        labels = st.assign_nearest(rows, state, True).select("id", "cluster")
        state = _state(rows.select("id", "vec").join(labels, "id"))
    return labels


@query(_DSQ + _lloyd_step(0) + " SELECT id, c AS cluster FROM l1")
def init_dsq_nearest(spark, d):
    return _lloyd_dsq(_part(spark, d), 4, 1)


@query(_DSQ + ", ".join(_lloyd_step(i) for i in range(3)) + " SELECT id, c AS cluster FROM l3")
def lloyd_dsq_e3(spark, d):
    return _lloyd_dsq(_part(spark, d), 4, 3)


@query(EMB + """, a AS (SELECT p.id, p.v AS cluster, (st.cnt - CASE WHEN p.u = p.v THEN 1 ELSE 0 END)::DOUBLE AS n,
    CASE WHEN p.u = p.v THEN st.dd - 2 * p.p + q.q ELSE st.dd END::DOUBLE AS dd, CASE WHEN p.u = p.v THEN p.p - q.q ELSE p.p END::DOUBLE AS p FROM p JOIN q USING (id) JOIN st ON st.c = p.v)
SELECT id, cluster, round(CASE WHEN n > 0 THEN dd / (n * (n + 1)) END, 5) AS mu, round(CASE WHEN n > 0 THEN p / n END, 5) AS delta FROM a""")
def appendix_terms(spark, d):
    """In fixed point, unscaled: quotients of small integers scaled down would end in halves at the last place."""
    rows = _emb(spark, d)
    return st.appendix_terms(rows, _state(rows), True).select("id", "cluster", F.round("mu", 5).alias("mu"), F.round("delta", 5).alias("delta"))


@query(EMB + """, cc AS (SELECT s.c, s.pos, s.s / st.cnt::DOUBLE AS x FROM s JOIN st USING (c))
SELECT a.c AS cluster, b.c AS near, round(sum(power(a.x - b.x, 2)), 3) AS dist2 FROM cc a JOIN cc b ON a.pos = b.pos AND a.c <> b.c GROUP BY a.c, b.c""")
def centroid_graph(spark, d):
    return st.candidate_table(_state(_emb(spark, d)), K).select("cluster", "near", F.round("dist2", 3).alias("dist2"))


@query(EMB + """, w AS (SELECT p.id, p.v, ((2 * p.p + q.q)::DOUBLE - st.dd::DOUBLE / st.cnt) / (st.cnt::DOUBLE + 1) AS won FROM p JOIN q USING (id) JOIN st ON st.c = p.v),
r AS (SELECT id, v AS cluster, row_number() OVER (PARTITION BY id ORDER BY won DESC, v)::INTEGER AS place FROM w) SELECT * FROM r WHERE place <= 4""")
def row_candidates(spark, d):
    rows = _emb(spark, d)
    return st.row_candidates(rows, _state(rows), 4, True)


@query(_gain_chain("part", 6, 2).replace(" SELECT id, c AS cluster FROM l2", " SELECT id, c AS cluster FROM l2 EXCEPT SELECT id, c FROM l1"))
def moved_between_epochs(spark, d):
    rows = _part(spark, d)
    return st.moved(_relational(rows, 6, 1), _relational(rows, 6, 2))


# --- measures over runs, on groups of the given tables


def _drift_rows(spark, d) -> DataFrame:
    return load_table(spark, d, "events").select("event_id", "ts", F.col("event_type").alias("method"), F.col("event_id").alias("epoch"), ((F.col("value") - 1) * (F.col("value") - 1)).alias("dist2"), F.col("value").alias("distortion"))


@query("SELECT label::VARCHAR AS method, count(*) AS runs, " + ", ".join(f"round(quantile_cont(embedding[1]::DOUBLE, {q}), 9) AS {c}" for q, c in ((0, "least"), (0.25, "q1"), (0.5, "median"), (0.75, "q3"), (1, "most"))) + " FROM embeddings GROUP BY label")
def run_summary(spark, d):
    runs = load_table(spark, d, "embeddings").select(F.col("label").cast("string").alias("method"), F.col("embedding")[0].cast("double").alias("distortion"))
    return metrics.run_summary(runs).select("method", "runs", *[r9(F.col(c)).alias(c) for c in ("least", "q1", "median", "q3", "most")])


@query("SELECT p_brand AS method, round(regr_slope(ln(p_retailprice), ln(p_size::DOUBLE)), 6) AS slope FROM part GROUP BY p_brand")
def time_slope(spark, d):
    return metrics.growth(load_table(spark, d, "part").withColumnRenamed("p_brand", "method"), "p_size", "p_retailprice").withColumn("slope", F.round("slope", 6))


@query("SELECT event_type AS method, min(event_id) AS epochs FROM events WHERE value <= 0.5 GROUP BY event_type")
def epochs_to(spark, d):
    return metrics.epochs_to(_drift_rows(spark, d), 0.5)


@query("SELECT o_orderpriority AS method, round((SELECT avg(o_totalprice) FROM orders WHERE o_orderpriority = '1-URGENT') / avg(o_totalprice), 9) AS ratio FROM orders GROUP BY o_orderpriority")
def speedup(spark, d):
    return metrics.speedup(load_table(spark, d, "orders").withColumnRenamed("o_orderpriority", "method"), "1-URGENT", "o_totalprice").withColumn("ratio", r9(F.col("ratio")))


@query("SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::INTEGER AS level, round(avg(l_quantity), 6) AS mean, min(l_quantity) AS least, max(l_quantity) AS most, count(*) AS runs FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def result_cube(spark, d):
    return metrics.result_cube(load_table(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], "l_quantity").withColumn("mean", F.round("mean", 6))


@query("SELECT event_type AS method, event_id AS epoch, value AS distortion, round(lag(value) OVER w - value, 9) AS gained, min(value) OVER w AS best FROM events WINDOW w AS (PARTITION BY event_type ORDER BY event_id)")
def best_so_far(spark, d):
    return metrics.best_so_far(_drift_rows(spark, d)).withColumn("gained", r9(F.col("gained")))


# --- streams, run here on whole tables


@query("WITH " + _BASE["part"] + """, e AS (SELECT id, c, unnest(v) AS val, generate_subscripts(v, 1) - 1 AS pos FROM x),
s AS (SELECT c, pos, sum(val)::BIGINT AS s FROM e WHERE id % 2 = 0 GROUP BY c, pos), q AS (SELECT id, sum(val * val)::BIGINT AS q FROM e GROUP BY id),
st AS (SELECT c, any_value(n) AS n, sum(s * s)::BIGINT AS dd FROM s JOIN (SELECT c, count(*) AS n FROM x WHERE id % 2 = 0 GROUP BY c) USING (c) GROUP BY c),
p AS (SELECT e.id, s.c, sum(e.val * s.s)::BIGINT AS p FROM e JOIN s USING (pos) WHERE e.id % 2 = 1 GROUP BY e.id, s.c),
w AS (SELECT id, c FROM (SELECT p.id, p.c, row_number() OVER (PARTITION BY p.id ORDER BY ((2 * p.p + q.q)::DOUBLE - st.dd::DOUBLE / st.n) / (st.n::DOUBLE + 1) DESC, p.c) AS r FROM p JOIN q USING (id) JOIN st USING (c)) WHERE r = 1),
z AS (SELECT id, c FROM x WHERE id % 2 = 0 UNION ALL SELECT id, c FROM w)
SELECT z.c::INTEGER AS cluster, count(DISTINCT e.id) AS cnt, e.pos::INTEGER AS pos, sum(e.val)::DOUBLE AS s FROM z JOIN e USING (id) GROUP BY z.c, e.pos""")
def stream_absorb(spark, d):
    """The odd rows arrive at the state of the even ones."""
    rows = features.part2(spark, d).select("id", F.transform(to_fixed(F.col("vec")), lambda x: x.cast("double")).alias("vec"), F.col("label").alias("cluster"))
    got = streams.absorb(rows.where("id % 2 = 1"), st.cluster_state(rows.where("id % 2 = 0")))
    return got.select("cluster", "cnt", F.posexplode("sum_vec").alias("pos", "s"))


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, round(avg((value - 1) * (value - 1)), 9) AS distortion, count(*) AS n FROM events GROUP BY 1")
def stream_drift(spark, d):
    return streams.drift(_drift_rows(spark, d)).withColumn("distortion", r9(F.col("distortion")))


_VERSIONS = "(SELECT (epoch(day) // 86400)::INTEGER AS version, day AS since FROM (SELECT DISTINCT date_trunc('day', ts)::TIMESTAMP + INTERVAL 6 HOUR AS day FROM events))"


@query(f"SELECT e.event_id, coalesce(v.version, 0)::INTEGER AS version FROM events e ASOF LEFT JOIN {_VERSIONS} v ON e.ts >= v.since")
def version_as_of(spark, d):
    """Events with the model version of the day, which comes into force at six; 0 before the first."""
    events = load_table(spark, d, "events")
    since = (F.date_trunc("day", "ts") + F.expr("INTERVAL 6 HOURS")).alias("since")
    versions = events.select(since).distinct().select(F.floor(F.unix_timestamp("since") / 86400).cast("int").alias("version"), "since")
    return streams.as_of(events.select("event_id", "ts"), versions).select("event_id", F.coalesce("version", F.lit(0)).alias("version"))


@query("SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def followed_by(spark, d):
    return streams.followed_by(load_table(spark, d, "events"), "click", "purchase")


# --- TF/IDF of the other text tables


def _tfidf_sql(source: str) -> str:
    return rf"""WITH src AS ({source}), tc AS (SELECT id, term, count(*) AS tf FROM (SELECT id, unnest(regexp_extract_all(lower(text), '\p{{L}}+')) AS term FROM src) GROUP BY id, term),
df AS (SELECT term, count(*) AS df, ln((SELECT count(DISTINCT id) FROM src)::DOUBLE / count(*)) AS idf FROM tc GROUP BY term),
top AS (SELECT * FROM df ORDER BY df DESC, term LIMIT 512), w AS (SELECT id, term, tf * idf AS w FROM tc JOIN top USING (term)), n AS (SELECT *, sqrt(sum(w * w) OVER (PARTITION BY id)) AS n FROM w)
SELECT id, term, round(CASE WHEN n > 0 THEN w / n ELSE 0 END, 9) AS weight FROM n"""


def _weights(docs: DataFrame, id_col: str) -> DataFrame:
    return features.tfidf(docs, 512, id_col=id_col).select("id", "term", r9(F.col("weight")).alias("weight"))


@query(_tfidf_sql("SELECT page_id AS id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages"))
def tfidf_pages(spark, d):
    return _weights(load_table(spark, d, "pages").select("page_id", features.without_tags(F.col("html")).alias("text")), "page_id")


@query(_tfidf_sql("SELECT conv_id AS id, text FROM conversations"))
def tfidf_conversations(spark, d):
    return _weights(load_table(spark, d, "conversations"), "conv_id")


@query(_tfidf_sql("SELECT item_id AS id, text FROM benchmark"))
def tfidf_benchmark(spark, d):
    return _weights(load_table(spark, d, "benchmark"), "item_id")


_method("mllib_kmeans", lambda r: external.mllib_kmeans(r, K))
_method("mllib_bisecting", lambda r: external.mllib_kmeans(r, K, bisecting=True))
_method("gain_kway_dsq_oversampled", lambda r: kway.gain_kway(r, K, "dsq_oversampled", engine="partitioned", max_epochs=3))
_method("lloyd_dsq_oversampled", lambda r: kway.lloyd(r, K, "dsq_oversampled", max_epochs=5))
_method("restarts", lambda r: kway.restarts(r, "gain_random_label", K)[1])


def _line4(method: str, spark, d) -> DataFrame:
    """One distributed run over the whole of line4, k = 64, with its rows a second."""
    rows = features.line4(spark, d).select("id", "vec")
    return spark.createDataFrame(workloads._timed(rows, 64, [method]), workloads.GROWTH)


def _workload(name: str, f):
    f.__name__ = name
    query()(f)


@query(_prefix("emb_double", "DOUBLE") + _APPROX + f""", b AS (SELECT y.*, g.gain, g.cnt_u FROM y JOIN g USING (id, v))
SELECT sum((abs(gain) > 1e-9 AND exact <> (gain > 0))::INTEGER)::BIGINT AS unequal, round(avg((exact <> approx)::INTEGER), 9) AS approx_differs, count(DISTINCT CASE WHEN gain > 1e-9 AND cnt_u > 1 THEN id END) AS improving,
    (SELECT count(*) FROM {_NEAR} a JOIN n ON n.id = a.id AND n.v = a.u WHERE a.d2 < n.d2) AS violations FROM b""")
def w18(spark, d):
    return workloads.w18(spark, d)


_GIVEN = {
    "emb64": "SELECT vec_id AS id, list_transform(embedding, lambda v: v::DOUBLE) AS v, label::VARCHAR AS c FROM embeddings",
    "emb64_scaled": "SELECT vec_id AS id, list_transform(embedding, lambda v: v::DOUBLE * (1 + vec_id % 5)) AS v, label::VARCHAR AS c FROM embeddings",
    "part2": "SELECT p_partkey AS id, [p_size::DOUBLE, p_retailprice / 100] AS v, (p_size % 8)::VARCHAR AS c FROM part",
    "acct1": "SELECT s_suppkey AS id, [s_acctbal / 1000] AS v, (s_nationkey % 3)::VARCHAR AS c FROM supplier",
    "line4": "SELECT row_number() OVER () AS id, [l_quantity, l_extendedprice / 1000, l_discount * 100, l_tax * 100] AS v, l_returnflag AS c FROM lineitem",
    "user7": "SELECT user_id AS id, [count(*) FILTER (event_type = 'click')::DOUBLE, count(*) FILTER (event_type = 'purchase'), count(*) FILTER (event_type = 'error'), count(*) FILTER (event_type = 'signup'), count(*) FILTER (event_type = 'view'), avg(value), max(value)] AS v, (user_id % 5)::VARCHAR AS c FROM events GROUP BY user_id",
    "cust4": "SELECT o_custkey AS id, [count(*)::DOUBLE, sum(o_totalprice), avg(o_totalprice), max(o_totalprice)] AS v, (o_custkey % 5)::VARCHAR AS c FROM orders GROUP BY o_custkey",
}


def _identities_sql(name: str) -> str:
    places = workloads.DIGITS.get(name, 3)
    return f"""(WITH x AS MATERIALIZED ({_GIVEN[name]}), e AS MATERIALIZED (SELECT id, c, unnest(v) AS val, generate_subscripts(v, 1) AS pos FROM x),
s AS (SELECT c, pos, sum(val) AS s, count(*) AS n FROM e GROUP BY c, pos), st AS (SELECT c, any_value(n) AS cnt, sum(s * s) AS dd FROM s GROUP BY c), xs AS (SELECT c, sum(val * val) AS xx FROM e GROUP BY c),
o AS (SELECT sum(cnt)::BIGINT AS n, sum(xx) AS total, sum(dd / cnt) AS score, sum(xx - dd / cnt) AS sse, sum(CASE WHEN cnt > 1 THEN 2 * cnt::DOUBLE / (cnt - 1) * (xx - dd / cnt) ELSE 0 END) AS pe FROM st JOIN xs USING (c)),
r AS (SELECT sum(power(e.val - s.s / s.n, 2)) AS by_row FROM e JOIN s USING (c, pos))
SELECT '{name}' AS rows, n, round(total, {places}) AS total, round(score, {places}) AS score, round(sse, {places}) AS sse, round(by_row, {places}) AS sse_by_row, round(sse / n, {places}) AS distortion, round(pe, {places}) AS pair_exact, round(2 * total - 2 * score, {places}) AS pair_approx, round((pe - (2 * total - 2 * score)) / pe, 6) AS pair_gap FROM o, r)"""


@query(" UNION ALL ".join(_identities_sql(x) for x in _GIVEN))
def w19(spark, d):
    return workloads.w19(spark, d)


for _name in ("w1", "w2", "w3", "w4", "w5", "w5_line4", "w10", "w11", "w12", "w13", "w14", "w15", "w16", "w17"):
    _workload(_name, lambda spark, d, _f=getattr(workloads, _name): _f(spark, d))
for _name, _m, _methods in (("w6", 8, kernels.FLAT), ("w7", 8, kernels.HIERARCHIES), ("w8", 16, kernels.FLAT), ("w9", 16, kernels.HIERARCHIES)):
    _workload(_name, lambda spark, d, _m=_m, _t=[x for x in workloads.TABLE if x in _methods]: workloads.w6(spark, d, _m, methods=_t))
_workload("w10_labels", lambda spark, d: workloads.w10(spark, d, cls="labels"))
_workload("gain_kway_line4", lambda spark, d: _line4("gain_random_label", spark, d))
_workload("gain_bisect_line4", lambda spark, d: _line4("gain_bisect_random_label", spark, d))
_workload("lloyd_line4", lambda spark, d: _line4("lloyd", spark, d))
_workload("w10_source", lambda spark, d: workloads.w10(spark, d, cls="source"))


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
