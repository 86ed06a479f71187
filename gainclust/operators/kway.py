"""Distributed clustering by score gains and its distributed baselines.

engine partitioned: each partition visits its rows in a new random order every epoch on a private copy of the
broadcast state. engine relational: every row proposes its best move against one frozen state; a hash-chosen share is
accepted. engine sequential: one task, the exact one-row-at-a-time rule, refused above LOCAL_ROWS. The engines end in
different labels; none is chosen by the size of the input.

In the first two a guard recomputes the score from data and halves what was accepted until the score has risen, so
frozen states cannot make the labels run in circles. Rows with labels are written once per epoch, without a shuffle,
and the files of the epoch before deleted; the driver holds k rows of state.

A hierarchy splits all leaves that its queue may want in one pass over their rows: a cluster is then a part of a node,
and a row is tested against the parts of its own node only. So its cost goes with the depth, not the number of nodes.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainclust.functions.vectors import dimension, norm2, portable_hash, to_fixed, unit
from gainclust.operators import kernels
from gainclust.operators.seeding import seed_dsq_oversampled
from gainclust.operators.state import MAX_STATE_BYTES, assign_nearest, best_moves, candidate_table, cluster_state, padded, row_candidates
from gainclust.sources.storage import discard, stored

LOCAL_ROWS = 200_000
SEEDS_A_PASS = 16


@dataclass
class ClusterResult:
    assignments: DataFrame
    k: int
    history: list[dict] = field(default_factory=list)
    nodes: list[dict] = field(default_factory=list)

    def state(self, rows: DataFrame) -> DataFrame:
        return cluster_state(rows.select("id", "vec").join(self.assignments, "id"))


def random_labels(rows: DataFrame, k: int, seed: int = 42) -> DataFrame:
    return rows.withColumn("cluster", (portable_hash(F.col("id"), seed) % k).cast("int"))


def _matrix(column) -> np.ndarray:
    flat = np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 0))


def _state(rows: DataFrame, k: int, d: int) -> tuple[np.ndarray, np.ndarray, float]:
    """Sum vectors, counts and the sum of squared norms; per partition in numpy, k rows to the driver."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s, cnt, xx = np.zeros((k, d)), np.zeros(k, np.int64), np.zeros(k)
        for b in batches:
            if not b.num_rows:
                continue
            x, c = _matrix(b.column(0)), b.column(1).to_numpy()
            np.add.at(s, c, x)
            cnt += np.bincount(c, minlength=k)
            xx += np.bincount(c, (x * x).sum(1), k)
        at = np.flatnonzero(cnt)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(cnt[at]), pa.array(xx[at]), pa.array(list(s[at]), pa.list_(pa.float64()))], names=["cluster", "cnt", "xx", "s"])

    kind = "cluster int, cnt long, xx double, s array<double>"
    parts = rows.select("vec", "cluster").mapInArrow(partial, kind)
    width = min(k, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    merged = parts.repartition(width, "cluster").mapInArrow(_added, kind)
    s, cnt, total = np.zeros((k, d)), np.zeros(k), 0.0
    got = merged.toArrow()  # k rows
    if got.num_rows:
        at = got["cluster"].to_numpy()
        s[at], cnt[at], total = _matrix(got["s"].combine_chunks()), got["cnt"].to_numpy(), float(got["xx"].to_numpy().sum())
    return s, cnt, total


def _added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The sums of the partial states of each cluster; vectors travel whole."""
    held: dict[int, list] = {}
    for b in batches:
        if not b.num_rows:
            continue
        for c, cnt, xx, s in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), _matrix(b.column(3))):
            if c in held:
                own = held[c]
                own[0], own[1], own[2] = own[0] + cnt, own[1] + xx, own[2] + s
            else:
                held[c] = [cnt, xx, s.copy()]
    rows = list(held.values())
    yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.list_(pa.float64()))], names=["cluster", "cnt", "xx", "s"])


def _check(k: int, d: int) -> None:
    if k * d * 8 > MAX_STATE_BYTES:
        raise ValueError(f"{k} clusters of {d} components do not fit a broadcast state; use a hierarchy")


def seeds(rows: DataFrame, k: int, how: str, seed: int = 42) -> list[list[float]]:
    """k seed vectors: the rows of least hash, or by squared distance (one pass per seed, an exponential race)."""
    h = portable_hash(F.col("id"), f"seed{seed}")
    if how == "random":
        return [r.vec for r in rows.orderBy(h, "id").select("vec").limit(k).collect()]
    out = [rows.orderBy(h, "id").select("vec").first().vec]
    held, done = rows.select("id", "vec", F.lit(float("inf")).alias("d2")), 0
    while len(out) < k:
        # distances to older seeds are written down, so the plan and the work of a pass stay bounded
        near = F.least("d2", *[_gap(v) for v in np.array(out[done:], np.float64)])
        if len(out) - done >= SEEDS_A_PASS:
            old, held, done = held, stored(held.withColumn("d2", near), "seeds"), len(out)
            if hasattr(old, "_stored_path"):
                discard(old)
            near = F.col("d2")
        u = (portable_hash(F.col("id"), f"race{seed}-{len(out)}") + 1) / F.lit(float(1 << 28))
        row = held.select("id", "vec", near.alias("d2")).where("d2 > 0").select(F.min(F.struct((-F.log(u) / F.col("d2")).alias("race"), "id", "vec")).alias("m")).first()
        if row is None or row.m is None:
            break
        out.append(row.m.vec)
    return out


def _gap(v):
    parts = F.array(*[F.lit(float(x)) for x in v])
    return F.aggregate(F.zip_with("vec", parts, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def nearest_labels(rows: DataFrame, centroids: np.ndarray) -> DataFrame:
    """Rows with the label of the nearest centroid; centroids are broadcast after a size check."""
    _check(*centroids.shape)
    shared = rows.sparkSession.sparkContext.broadcast(centroids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                label = kernels.nearest(_matrix(b.column(1)), shared.value).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(label)], names=["id", "vec", "cluster"])

    return rows.select("id", "vec").mapInArrow(run, "id long, vec array<double>, cluster int")


def initial(rows: DataFrame, k: int, init, seed: int = 42) -> DataFrame:
    rows = rows.select("id", "vec")
    if isinstance(init, DataFrame):
        return rows.join(init.select("id", F.col("cluster").cast("int").alias("cluster")), "id")
    if init == "random_label":
        return random_labels(rows, k, seed)
    if init == "dsq_oversampled":
        return nearest_labels(rows, seed_dsq_oversampled(rows, k, seed=seed))
    if init in ("seed_nearest", "dsq_nearest"):
        return nearest_labels(rows, np.array(seeds(rows, k, "random" if init == "seed_nearest" else "dsq", seed), np.float64))
    raise ValueError(f"unknown start {init!r}")


def _doubles(rows: DataFrame) -> DataFrame:
    return rows.select("id", F.transform("vec", lambda x: x.cast("double")).alias("vec"))


def gain_kway(
    rows: DataFrame, k: int, init="random_label", move: str = "best", engine: str = "partitioned", max_epochs: int = 20, tol: float = 0.0, seed: int = 42, share: int = 1, candidates: int | None = None,
    candidate_mode: str = "row", warm_epochs: int = 3, scan: str = "rotated", min_move_ratio: float = 0.0, waves: int = 1, fixed: bool = False,
) -> ClusterResult:
    """Cluster (id, vec) rows into k by score gains; init is a start or a table (id, cluster).

    share: a relational round accepts one proposal in this many. candidates: after warm_epochs only so many clusters
    are tested, those a row would win most in (candidate_mode row) or of the centroids nearest to its cluster's
    (cluster). waves: the partitioned engine renews the state so many times an epoch. It stops when an epoch moves no
    more than min_move_ratio of the rows, or raises the score by no more than the share tol.
    """
    n = rows.count()
    if not 1 <= k <= max(n, 1):
        raise ValueError(f"k = {k} of {n} rows")
    if move not in ("best", "first") or candidate_mode not in kernels.CANDIDATES or scan not in ("rotated", "ascending"):
        raise ValueError(f"unknown move {move!r}, candidate mode {candidate_mode!r} or scan {scan!r}")
    if engine == "sequential":
        return local(rows, lambda x, own: kernels.gain_kway(x, k, own if own is not None else init, move, max_epochs, tol, seed, candidates, warm_epochs, candidate_mode, scan, min_move_ratio), init, k)
    if engine == "relational":
        return _relational(rows, k, init, move, max_epochs, seed, share, fixed, candidates, candidate_mode, warm_epochs)
    if engine != "partitioned":
        raise ValueError(f"unknown engine {engine!r}")
    rows = _doubles(rows)
    d = dimension(rows)
    _check(k, d)
    labelled = initial(rows, k, init, seed).select("id", "vec", "cluster")
    near = (candidates, candidate_mode, warm_epochs) if candidates and candidates < k else None
    held, history = _moves(labelled, 1, k, d, n, move, scan, max_epochs, tol, min_move_ratio, seed, waves, near)
    return ClusterResult(held.select("id", "cluster"), k, history)


def _node_scores(s: np.ndarray, cnt: np.ndarray, parts: int) -> np.ndarray:
    each = np.where(cnt > 0, (s * s).sum(1) / np.maximum(cnt, 1), 0.0)
    return each.reshape(-1, parts).sum(1)


def _moves(labelled: DataFrame, nodes: int, parts: int, d: int, n: int, move: str, scan: str, max_epochs: int, tol: float, min_move_ratio: float, seed: int, waves: int = 1, near: tuple | None = None, splitter: str = "gain") -> tuple[DataFrame, list[dict]]:
    """Epochs of moves within each node, cluster = node * parts + part, until no node's score rises: stored rows
    (id, vec, cluster, near) and the history. A node whose score has not risen is done and passed over from then on."""
    spark, k = labelled.sparkSession, nodes * parts
    held = stored(labelled.select("id", "vec", "cluster", F.col("cluster").alias("prev"), F.lit(0).cast("long").alias("cost"), F.lit(None).cast("array<int>").alias("near")), "epoch")
    kind = "id long, vec array<double>, cluster int, prev int, cost long, near array<int>"
    file, history = held, []
    s, cnt, total = _state(held, k, d)
    g = _node_scores(s, cnt, parts)
    least = 1e-12 * total / max(n, 1)
    open_ = np.ones(nodes, bool)
    by_row = False
    for epoch in range(1, max_epochs + 1):
        began, moved_all, compared, before, shares = time.time(), 0, 0, float(g.sum()), 1.0
        table = None
        if near and epoch > near[2]:
            if near[1] == "cluster":
                table, compared = kernels.nearest_centroids(s, cnt, near[0]), k * (k - 1)
            elif not by_row:
                # the candidates of every row are written with it once
                by_row, compared = True, n * k
                state = spark.sparkContext.broadcast((s, cnt))

                def choose(batches: Iterator[pa.RecordBatch], state=state) -> Iterator[pa.RecordBatch]:
                    for b in batches:
                        if b.num_rows:
                            found = kernels.nearest_by_gain(_matrix(b.column(1)), *state.value, near[0])
                            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(list(found.astype(np.int32)), pa.list_(pa.int32()))], names=b.schema.names)

                old, held = file, stored(held.mapInArrow(choose, kind), "epoch")
                file = held
                discard(old)
        for wave in range(waves):
            shared = spark.sparkContext.broadcast((s, cnt, open_, table))

            def visit(batches: Iterator[pa.RecordBatch], shared=shared, epoch=epoch, wave=wave, by_row=by_row) -> Iterator[pa.RecordBatch]:
                s, cnt, going, table = shared.value
                s, cnt = s.copy(), cnt.copy()
                for b in batches:
                    if not b.num_rows:
                        continue
                    x, labels = _matrix(b.column(1)), b.column(2).to_numpy().astype(np.int64)
                    new, cost, xx = labels.copy(), np.zeros(len(labels), np.int64), (x * x).sum(1)
                    mine = going[labels // parts]
                    if waves > 1:
                        mine &= b.column(6).to_numpy() == wave
                    rows = np.flatnonzero(mine)
                    if splitter == "lloyd":
                        for i in np.unique(labels[rows] // parts).tolist():
                            at, own = rows[labels[rows] // parts == i], slice(i * parts, (i + 1) * parts)
                            full = np.flatnonzero(cnt[own] > 0)
                            new[at] = i * parts + full[kernels.nearest(x[at], (s[own] / np.maximum(cnt[own], 1)[:, None])[full])]
                        cost[0] = len(rows) * parts
                    elif by_row or table is not None:
                        who = np.stack(b.column(5).to_numpy(zero_copy_only=False)).astype(np.int64) if by_row else table
                        cost[0] = kernels.one_pass(x, xx, new, s, cnt, rows, move, least, who, epoch, scan, not by_row)[1]
                    else:
                        # rows come by node, in a new order every epoch
                        edge = np.flatnonzero(np.diff(labels[rows] // parts)) + 1
                        for at in np.split(rows, edge) if len(rows) else ():
                            i = int(labels[at[0]] // parts)
                            own, part = slice(i * parts, (i + 1) * parts), new[at] - i * parts
                            y, view = cnt[own], s[own]
                            cost[0] += kernels.one_pass(x[at], xx[at], part, view, y, np.arange(len(at)), move, least, None, epoch, scan)[1]
                            new[at] = part + i * parts
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(new.astype(np.int32)), pa.array(labels.astype(np.int32)), pa.array(cost), b.column(5)], names=["id", "vec", "cluster", "prev", "cost", "near"])

            turn = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(waves)).cast("int").alias("turn")
            ordered = held.sortWithinPartitions(F.floor(F.col("cluster") / parts), F.xxhash64("id", F.lit(seed), F.lit(epoch)))
            tried = stored(ordered.select("id", "vec", "cluster", "prev", "cost", "near", turn).mapInArrow(visit, kind), "epoch")
            compared += tried.agg(F.sum("cost")).first()[0] or 0
            halvings = np.zeros(nodes, np.int64)
            now, s2, cnt2, moved = _guarded(held, tried, g, s, cnt, nodes, parts, d, halvings, open_, epoch, seed, splitter)
            moved_all += moved
            shares = float(0.5 ** halvings.max(initial=0))
            s, cnt, g = s2, cnt2, _node_scores(s2, cnt2, parts)
            old, file, held = file, now, now
            if file is not tried:
                discard(tried)
            discard(old)
        after = float(g.sum())
        history.append({"epoch": epoch, "moves": moved_all, "score": after, "sse": max(total - after, 0.0), "distortion": max(total - after, 0.0) / max(n, 1), "comparisons": int(compared), "accepted_share": shares, "seconds": time.time() - began})
        if not open_.any() or moved_all <= min_move_ratio * n or after <= before or (tol and after - before <= tol * abs(before)):
            break
    return held, history


def _guarded(held: DataFrame, tried: DataFrame, g: np.ndarray, s: np.ndarray, cnt: np.ndarray, nodes: int, parts: int, d: int, halvings: np.ndarray, open_: np.ndarray, epoch: int, seed: int, splitter: str) -> tuple[DataFrame, np.ndarray, np.ndarray, int]:
    """The tried labels where their node's score has risen; elsewhere half of the moves, a quarter, and so on, at last
    the single best one; a node for which even that fails keeps its labels and is closed (in open_)."""
    k, now = nodes * parts, tried
    s2, cnt2, _ = _state(now, k, d)
    g2 = _node_scores(s2, cnt2, parts)
    node = F.floor(F.col("cluster") / parts).cast("int")
    changed = {r.node: r.n for r in tried.where("cluster <> prev").groupBy(node.alias("node")).agg(F.count(F.lit(1)).alias("n")).collect()}
    moved = np.array([changed.get(i, 0) for i in range(nodes)])
    open_ &= moved > 0
    worse = open_ & (g2 <= g)
    while splitter == "gain" and (worse & (halvings <= 6)).any():
        halvings[worse] += 1
        shared = tried.sparkSession.sparkContext.broadcast((halvings.copy(), worse.copy()))
        thinned = _thinned(tried, shared, parts, epoch, seed)
        s2, cnt2, _ = _state(thinned, k, d)
        g2 = _node_scores(s2, cnt2, parts)
        worse, now = open_ & (g2 <= g), thinned
    if worse.any():
        if splitter == "gain":
            one = relational_epoch(held.select("id", "vec", "cluster"), k, d, epoch, seed, 1, one=True, parts=parts)
            one = one.select("id", F.col("cluster").alias("best"))
        else:
            one = held.select("id", F.col("cluster").alias("best"))  # the classic loop is at its end
        bad = held.sparkSession.createDataFrame([(int(i),) for i in np.flatnonzero(worse)], "bad int")
        base = now.join(F.broadcast(bad), node == F.col("bad"), "left").join(one, "id", "left")
        now = base.select("id", "vec", F.when(F.col("bad").isNotNull(), F.col("best")).otherwise(F.col("cluster")).cast("int").alias("cluster"), "prev", "cost", "near")
        now = stored(now, "epoch")
        s2, cnt2, _ = _state(now, k, d)
        open_ &= ~worse | (_node_scores(s2, cnt2, parts) > g)
    elif now is not tried:
        now = stored(now, "epoch")
    return now, s2, cnt2, int(moved.sum()) if now is tried else now.where("cluster <> prev").count()


def _thinned(tried: DataFrame, shared, parts: int, epoch: int, seed: int) -> DataFrame:
    """Of the moves in nodes with halvings only those of one row in 2^halvings."""
    h = portable_hash(F.col("id"), f"{seed}-{epoch}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        halvings, _ = shared.value
        for b in batches:
            new, old, draw = (b.column(i).to_numpy().astype(np.int64) for i in (2, 3, 6))
            keep = draw % (1 << halvings[new // parts]) == 0
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.where(keep, new, old).astype(np.int32)), *b.columns[3:6]], names=["id", "vec", "cluster", "prev", "cost", "near"])

    return tried.select("id", "vec", "cluster", "prev", "cost", "near", h.alias("draw")).mapInArrow(run, "id long, vec array<double>, cluster int, prev int, cost long, near array<int>")


def relational_epoch(labelled: DataFrame, k: int, d: int, epoch: int, seed: int, share: int, move: str = "best", fixed: bool = False, one: bool = False, parts: int | None = None, near: DataFrame | None = None) -> DataFrame:
    """One round of proposals against the frozen state, one in `share` accepted by hash: (id, vec, cluster, prev).

    one: only the best proposal (with parts: of each node) is accepted; its gain is exact, so the score rises.
    """
    state = padded(cluster_state(labelled, fixed), k, d, fixed)
    moves = best_moves(labelled, state, fixed, move == "first" and not one, parts=parts, near=near)
    if one:
        first = F.max(F.struct("gain", (-F.col("id")).alias("neg"), "id", "v")).alias("m")
        moves = moves.groupBy(F.floor(F.col("u") / (parts or k))).agg(first).select("m.id", "m.v")
    moves = moves.select("id", "v")
    keep = F.lit(True) if one else portable_hash(F.col("id"), f"{seed}-{epoch}") % share == 0
    return labelled.join(moves, "id", "left").select("id", "vec", F.when(keep & F.col("v").isNotNull(), F.col("v")).otherwise(F.col("cluster")).cast("int").alias("cluster"), F.col("cluster").alias("prev"))


def _relational(rows: DataFrame, k: int, init, move: str, max_epochs: int, seed: int, share: int, fixed: bool, candidates: int | None = None, candidate_mode: str = "row", warm_epochs: int = 3) -> ClusterResult:
    base = rows.select("id", to_fixed(F.col("vec")).alias("vec")) if fixed else _doubles(rows)
    d = dimension(base)
    held = stored(initial(_doubles(base), k, init, seed).select("id", "vec", "cluster"), "epoch")
    value = lambda df: cluster_state(df, fixed).agg(F.sum(F.col("dd").cast("double") / F.col("cnt")), F.sum("xx").cast("double"), F.sum("cnt")).first()
    g, total, n = value(held)
    out, file, near = ClusterResult(held, k), held, None
    for epoch in range(1, max_epochs + 1):
        began, width, one = time.time(), share, False
        compared = n * (k - 1)
        if candidates and candidates < k and epoch > warm_epochs:
            if candidate_mode == "cluster":
                near, compared = candidate_table(cluster_state(held, fixed), candidates), n * candidates + k * (k - 1)
            else:
                compared = n * candidates + (n * k if near is None else 0)
                near = near or stored(row_candidates(held, cluster_state(held, fixed), candidates, fixed).select("id", "cluster"), "near")
        while True:
            tried = stored(relational_epoch(held, k, d, epoch, seed, width, move, fixed, one, near=near), "epoch")
            moved = tried.where("cluster <> prev").count()
            after = value(tried)[0] if moved else g
            if after > g or one:
                break
            # halve what is accepted, at last to the single best proposal; only if there is none are we done
            width *= 2
            one = not moved or width > 64 * share
            discard(tried)
        if moved and after > g:
            held = tried.select("id", "vec", "cluster")
            discard(file)
            file = tried
        best = max(after, g)
        out.history.append({"epoch": epoch, "moves": moved, "score": best, "sse": max(total - best, 0.0), "distortion": max(total - best, 0.0) / max(n, 1), "comparisons": compared, "accepted_share": 1 / width, "seconds": time.time() - began})
        if not moved or after <= g:
            break
        g = after
    out.assignments = held.select("id", "cluster")
    return out


def local(rows: DataFrame, method, init=None, k: int = 1) -> ClusterResult:
    """Run a numpy method over all rows in one task; refused above LOCAL_ROWS."""
    n = rows.count()
    if n > LOCAL_ROWS:
        raise ValueError(f"{n} rows are too many for one task ({LOCAL_ROWS})")
    given = isinstance(init, DataFrame)
    data = rows.select("id", "vec")
    data = data.join(init.select("id", "cluster"), "id") if given else data.withColumn("cluster", F.lit(0))
    got = data.orderBy("id").toArrow()  # bounded above
    x = _matrix(got["vec"].combine_chunks())
    run = method(x, got["cluster"].to_numpy().astype(np.int64) if given else None)
    table = pa.table({"id": got["id"], "cluster": pa.array(run.labels.astype(np.int32))})
    return ClusterResult(rows.sparkSession.createDataFrame(table), run.k, run.history, run.nodes)


def gain_split(
    rows: DataFrame, k: int, s: int = 2, init: str = "random_label", priority: str = "size", splitter: str = "gain", seed: int = 42, move: str = "best", engine: str = "partitioned",
    local_rows: int = LOCAL_ROWS, max_epochs: int | None = None, share: int = 2, fixed: bool = False,
) -> ClusterResult:
    """Hierarchy of s-way splits: the first leaf of the queue (priority size: most rows; avg_pair: greatest mean distance
    of its pairs) is split until k leaves stand.

    In a round all leaves that the queue may want next are split together. Nodes over local_rows rows are split by the
    partitioned engine, smaller ones by the sequential rule, one task each; engine relational splits every node by
    max_epochs frozen rounds of joins and aggregates, without Python on executors. Then the queue is replayed on the
    driver from counts, sums and squared norms of the nodes, so the leaves are those of splitting one after the other.
    max_epochs: of a split; 200 where none is given, in the partitioned engine 20 and in frozen rounds 2. The history
    counts for nodes split in tasks the comparisons of one pass.
    """
    if move == "first":
        raise ValueError("first moves are for the flat method")
    n = rows.count()
    if s < 2 or not 1 <= k <= max(n, 1) or priority not in kernels.PRIORITIES or splitter not in ("gain", "lloyd") or engine not in ("partitioned", "relational", "sequential"):
        raise ValueError(f"s = {s}, k = {k} of {n} rows, priority {priority!r}, splitter {splitter!r}, engine {engine!r}")
    if engine == "sequential":
        return local(rows, lambda x, _: kernels.hierarchy(x, k, splitter, init, s, priority, seed, max_epochs=max_epochs or 200), k=k)
    if engine == "relational" and (splitter, init) != ("gain", "random_label"):
        raise ValueError("relational splits are by gains from random labels")
    began = time.time()
    base = rows.select("id", to_fixed(F.col("vec")).alias("vec")) if fixed else _doubles(rows)
    d = dimension(base)
    held = stored(base.select("id", "vec", F.lit("0").alias("node")), "nodes")
    tree = _Tree(s, k, priority)
    tree.add(_node_states(held, d))
    total, compared, rounds = tree.xx["0"], 0, 0
    while wanted := tree.wanted():
        rounds += 1
        names = dict(wanted)
        large = [x for x in names if tree.cnt[x] > local_rows or engine == "relational"]
        small = [x for x in names if x not in large]
        spark = rows.sparkSession
        numbered = {x: i if x in large else -1 for i, x in enumerate(large + small)}
        # rows may lie below the node, if it has been split into more parts than are wanted now
        below = [(p, x, names[x], numbered[x]) for p in tree.paths if (x := tree.above(p, names))]
        found = held.join(F.broadcast(spark.createDataFrame(below, "node string, top string, parts int, g int")), "node", "left")
        done = [found.where("top IS NULL").select("id", "vec", "node")]
        spent = []
        for parts in sorted({names[x] for x in large}):  # all s; at the end the last node may have fewer
            own = {x: numbered[x] for x in large if names[x] == parts}
            line = {g: i for i, g in enumerate(own.values())}
            index = F.element_at(F.create_map(*[F.lit(v) for pair in line.items() for v in pair]), F.col("g"))
            part = found.where(F.col("g").isin(list(line))).select("id", "vec", "top", index.alias("g"))
            if engine == "relational":
                labelled, cost = _split_frozen(part, len(own), parts, d, max_epochs or 2, seed, share, fixed)
            else:
                labelled, cost = _split_large(part, len(own), parts, d, init, splitter, seed, max_epochs or 20)
            compared += cost
            spent.append(labelled)
            mine = spark.createDataFrame([(i, x) for i, x in enumerate(own)], "at int, top string")
            done.append(labelled.join(F.broadcast(mine), F.floor(F.col("cluster") / parts) == F.col("at")).select("id", "vec", F.concat("top", F.lit("."), (F.col("cluster") % parts).cast("string")).alias("node")))
        if small:
            # with the queue by size no leaf of fewer than n / k rows is ever split, so the whole subtree is bounded by it
            least = n / k if priority == "size" else None
            subtree = _subtree(splitter, init, s, priority, seed, least, max_epochs or 200)
            done.append(found.where("g = -1").select("id", "vec", "top", "parts").groupBy("top").applyInPandas(subtree, "id long, vec array<double>, node string"))
        now = done[0]
        for x in done[1:]:
            now = now.unionByName(x)
        old, held = held, stored(now, "nodes")
        discard(old)
        discard(*spent)
        tree.add(_node_states(held, d), names)
    compared += tree.visited(local_rows if engine != "relational" else 0)
    spark = rows.sparkSession
    leaves = tree.standing()
    number = {x: i for i, x in enumerate(leaves)}
    pairs = [(p, number[tree.above(p, number)]) for p in tree.paths]
    labels = spark.createDataFrame(pairs, "node string, cluster int")
    out = held.join(F.broadcast(labels), "node").select("id", "cluster")
    sse = sum(tree.error(x) for x in leaves)
    history = [{"epoch": 1, "moves": n, "score": total - sse, "sse": sse, "distortion": sse / max(n, 1), "comparisons": compared, "rounds": rounds, "seconds": time.time() - began}]
    return ClusterResult(out, len(leaves), history, tree.table(leaves))


class _Tree:
    """The nodes split so far, on the driver: counts, sums and squared norms, at most a state's size."""

    def __init__(self, s: int, k: int, priority: str):
        self.s, self.k, self.priority = s, k, priority
        self.cnt: dict[str, int] = {}
        self.xx: dict[str, float] = {}
        self.sum: dict[str, np.ndarray] = {}
        self.children: dict[tuple[str, int], list[str]] = {}
        self.dead: set[tuple[str, int]] = set()
        self.paths: list[str] = []
        self.order: list[str] = []

    def add(self, states: dict[str, tuple[int, float, np.ndarray]], names: dict[str, int] | None = None) -> None:
        """What the rows' present nodes are; names: the nodes just split, with their parts."""
        self.paths = sorted(states)
        if names is None:
            (self.cnt["0"], self.xx["0"], self.sum["0"]) = states["0"]
            return
        for top, parts in names.items():
            below: dict[str, set[str]] = {}
            own: dict[str, list] = {}
            for path in self.paths:
                if path != top and not path.startswith(top + "."):
                    continue
                at = path
                while True:
                    if at in own:
                        own[at] = [a + b for a, b in zip(own[at], states[path])]
                    else:
                        own[at] = list(states[path])
                    if at == top:
                        break
                    up = at.rpartition(".")[0]
                    below.setdefault(up, set()).add(at)
                    at = up
            for x, (c, q, v) in own.items():
                if x != top:
                    self.cnt[x], self.xx[x], self.sum[x] = c, q, v
            for x, found in below.items():
                n_parts = parts if x == top else min(self.s, self.cnt[x])
                self.children[x, n_parts] = sorted(found, key=_natural)
                if len(found) < 2:
                    self.dead.add((x, n_parts))
            if top not in below:
                self.dead.add((top, parts))

    def error(self, x: str) -> float:
        return max(self.xx[x] - float(self.sum[x] @ self.sum[x]) / self.cnt[x], 0.0)

    def _key(self, x: str) -> float:
        n = self.cnt[x]
        return -n if self.priority == "size" else -(2 * self.error(x) / (n - 1))

    def _queued(self, x: str) -> bool:
        return self.cnt[x] > 1 and self.error(x) > 1e-12 * max(self.xx[x], 1e-300)

    def _replay(self) -> tuple[list[tuple[str, int]], list[str]]:
        """Nodes whose split is wanted but not known, the first of them for sure; leaves as far as known."""
        queue = [(self._key("0"), "0")] if self._queued("0") else []
        leaves, wanted, stand = 1, [], {"0"}
        self.order = []
        while leaves < self.k and queue:
            _, x = heapq.heappop(queue)
            parts = min(self.s, self.k - leaves + 1, self.cnt[x])
            if (x, parts) in self.dead:
                continue
            if (x, parts) not in self.children:
                if parts == self.s or not wanted:
                    wanted.append((x, parts))
                leaves += parts - 1
                continue
            found = self.children[x, parts]
            self.order.append(x)
            leaves += len(found) - 1
            stand.discard(x)
            stand.update(found)
            for y in found:
                if self._queued(y):
                    heapq.heappush(queue, (self._key(y), y))
        return wanted, sorted(stand, key=_natural)

    def wanted(self) -> list[tuple[str, int]]:
        return self._replay()[0]

    def standing(self) -> list[str]:
        return self._replay()[1]

    def above(self, path: str, names) -> str:
        """The node itself or the one over it that is among names; empty if none is."""
        while path and path not in names:
            path = path.rpartition(".")[0]
        return path

    def visited(self, over: int) -> int:
        """Comparisons of one pass over the nodes that were split in tasks."""
        return sum(self.cnt[x] * (self.s - 1) for x in self.order if self.cnt[x] <= over)

    def table(self, leaves: list[str]) -> list[dict]:
        rank = {x: i + 1 for i, x in enumerate(self.order)}
        return [{"node_id": x, "parent": x.rpartition(".")[0] or None, "depth": x.count("."), "cnt": int(self.cnt[x]), "sse": self.error(x), "split_rank": rank.get(x), "is_leaf": x not in rank} for x in [*self.order, *leaves]]


def _natural(path: str) -> list[int]:
    return [int(x) for x in path.split(".")]


def _node_states(held: DataFrame, d: int) -> dict[str, tuple[int, float, np.ndarray]]:
    """Count, squared norms and sum vector of every node that rows are in."""
    names = sorted(r.node for r in held.select("node").distinct().collect())  # leaves: about k of them
    _check(len(names), d)
    shared = held.sparkSession.createDataFrame(list(zip(names, range(len(names)))), "node string, cluster int")
    kind = "cluster int, cnt long, xx double, s array<double>"

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: dict[int, list] = {}
        for b in batches:
            if not b.num_rows:
                continue
            x, c = _matrix(b.column(0)), b.column(1).to_numpy()
            for i in np.unique(c).tolist():
                y = x[c == i]
                one = [len(y), float((y * y).sum()), y.sum(0)]
                out[i] = [a + e for a, e in zip(out[i], one)] if i in out else one
        rows = list(out.values())
        yield pa.RecordBatch.from_arrays([pa.array(list(out), pa.int32()), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.list_(pa.float64()))], names=["cluster", "cnt", "xx", "s"])

    rows = held.join(F.broadcast(shared), "node").select(F.transform("vec", lambda x: x.cast("double")).alias("vec"), "cluster")
    width = min(len(names) or 1, int(held.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    got = rows.mapInArrow(partial, kind).repartition(width, "cluster").mapInArrow(_added, kind).toArrow()
    if not got.num_rows:
        return {"0": (0, 0.0, np.zeros(d))}
    return {names[c]: (n, q, v) for c, n, q, v in zip(got["cluster"].to_pylist(), got["cnt"].to_pylist(), got["xx"].to_pylist(), _matrix(got["s"].combine_chunks()))}


def _subtree(splitter: str, init: str, s: int, priority: str, seed: int, least: float | None, max_epochs: int):
    """A whole subtree in one task down to nodes of `least` rows; or a single split."""

    def run(key, pdf):
        pdf = pdf.sort_values("id", kind="stable")
        x = np.stack(pdf["vec"].to_numpy()).astype(np.float64)
        parts = int(pdf["parts"].iloc[0])
        deep = least is not None and parts == s and len(x) >= least
        got = kernels.hierarchy(x, len(x) if deep else min(parts, len(x)), splitter, init, parts, priority, seed, max_epochs=max_epochs, root=key[0], least=least if deep else 0)
        names = np.array([nd["node_id"] for nd in got.nodes if nd["is_leaf"]], dtype=object)
        return pdf.assign(node=names[got.labels])[["id", "vec", "node"]]

    return run


def _split_large(part: DataFrame, nodes: int, s: int, d: int, init: str, splitter: str, seed: int, max_epochs: int) -> tuple[DataFrame, int]:
    """Split rows (id, vec, top, g) of every node g by the partitioned engine, all nodes at once."""
    _check(nodes * s, d)
    rows = stored(part, "open")
    seeds_too = init if splitter == "gain" else "dsq_nearest" if init == "dsq_nearest" else "seed_nearest"
    if seeds_too == "random_label":
        first = (portable_hash(F.concat_ws(":", "top", "id"), seed) % s).cast("int")
        labelled = rows.select("id", "vec", (F.col("g") * s + first).alias("cluster"))
    elif seeds_too in ("seed_nearest", "dsq_nearest"):
        centres = _node_seeds(rows, nodes, s, seeds_too == "dsq_nearest", seed)
        shared = rows.sparkSession.sparkContext.broadcast(centres)

        def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    x, g = _matrix(b.column(1)), b.column(2).to_numpy()
                    label = np.empty(len(x), np.int32)
                    for i in np.unique(g).tolist():
                        label[g == i] = i * s + kernels.nearest(x[g == i], np.array(shared.value[i]))
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(label)], names=["id", "vec", "cluster"])

        labelled = rows.select("id", "vec", "g").mapInArrow(nearest, "id long, vec array<double>, cluster int")
    else:
        raise ValueError(f"unknown start {init!r}")
    held, history = _moves(labelled, nodes, s, d, rows.count(), "best", "rotated", max_epochs, 0.0, 0.0, seed, splitter=splitter)
    discard(rows)
    return held, sum(h["comparisons"] for h in history)


def _node_seeds(rows: DataFrame, nodes: int, s: int, far: bool, seed: int) -> list[list]:
    """Per node the rows of least hash, or one such row and then exponential races by squared distance."""
    order = Window.partitionBy("g").orderBy(portable_hash(F.concat_ws(":", "top", "id"), f"seed{seed}"), "id")
    few = rows.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= (1 if far else s))
    out: list[list] = [[] for _ in range(nodes)]
    for r in few.orderBy("g", "nth").select("g", "vec").collect():  # parts of each node
        out[r.g].append(r.vec)
    for nth in range(1, s) if far else ():
        shared = rows.sparkSession.sparkContext.broadcast([np.array(c) for c in out])

        def race(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    x, g, u = _matrix(b.column(0)), b.column(1).to_numpy(), b.column(2).to_numpy()
                    keep, time_ = [], np.empty(len(x))
                    for i in np.unique(g).tolist():
                        at = np.flatnonzero(g == i)
                        d2 = ((x[at][:, None, :] - shared.value[i][None]) ** 2).sum(2).min(1)
                        time_[at] = np.where(d2 > 0, -np.log(u[at]) / np.maximum(d2, 1e-300), np.inf)
                        keep.append(at[int(np.argmin(time_[at]))])
                    keep = np.array([i for i in keep if np.isfinite(time_[i])], np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(g[keep]), pa.array(time_[keep]), b.column(0).take(pa.array(keep))], names=["g", "race", "vec"])

        u = ((portable_hash(F.concat_ws(":", "top", "id"), f"race{seed}-{nth}") + 1) / F.lit(float(1 << 28))).alias("u")
        runs = rows.select("vec", "g", u).mapInArrow(race, "g int, race double, vec array<double>")
        for r in runs.groupBy("g").agg(F.min(F.struct("race", "vec")).alias("m")).collect():  # one row of each node
            out[r.g].append(r.m.vec)
    return out


def _split_frozen(part: DataFrame, nodes: int, s: int, d: int, epochs: int, seed: int, share: int, fixed: bool) -> tuple[DataFrame, int]:
    """Split rows (id, vec, top, g) by rounds of proposals against frozen states, one in `share` accepted."""
    first = (portable_hash(F.concat_ws(":", "top", "id"), seed) % s).cast("int")
    held = stored(part.select("id", "vec", (F.col("g") * s + first).cast("int").alias("cluster")), "epoch")
    n = held.count()
    for epoch in range(1, epochs + 1):
        now = stored(relational_epoch(held, nodes * s, d, epoch, seed, share, fixed=fixed, parts=s).drop("prev"), "epoch")
        discard(held)
        held = now
    return held, n * (s - 1) * epochs


def gain_bisect(rows: DataFrame, k: int, **options) -> ClusterResult:
    return gain_split(rows, k, 2, **options)


def cosine_bisect(rows: DataFrame, k: int, seed: int = 42, **options) -> ClusterResult:
    """Repeated bisection by average cosine: the gain hierarchy on unit vectors, at any size.

    Vectors within 1e-6 of unit length stay as they are, so on unit rows the result is the gain hierarchy's.
    """
    near = F.abs(F.sqrt(norm2(F.col("vec"))) - 1) <= 1e-6
    ready = _doubles(rows).select("id", F.when(near, F.col("vec")).otherwise(unit(F.col("vec"))).alias("vec"))
    return gain_split(ready, k, init="seed_nearest", seed=seed, **options)


def refine(result: ClusterResult, rows: DataFrame, max_epochs: int = 20, move: str = "best", **options) -> ClusterResult:
    """Flat gain moves from the labels of any method."""
    return gain_kway(rows, result.k, result.assignments, move, max_epochs=max_epochs, **options)


def lloyd(rows: DataFrame, k: int, seeding: str = "random", max_epochs: int = 30, seed: int = 42) -> ClusterResult:
    """The classic loop, distributed: broadcast centroids, nearest labels, sums by cluster."""
    rows = stored(_doubles(rows), "rows")
    d, n = dimension(rows), rows.count()
    c = seed_dsq_oversampled(rows, k, seed=seed) if seeding == "dsq_oversampled" else np.array(seeds(rows, k, seeding, seed), np.float64)
    k = len(c)  # fewer where there are fewer different rows
    out = ClusterResult(rows, k)
    before = None
    for epoch in range(1, max_epochs + 1):
        began = time.time()
        labelled = nearest_labels(rows, c)
        s, cnt, total = _state(labelled, k, d)
        g = kernels.score(s, cnt)
        c = np.where(cnt[:, None] > 0, s / np.maximum(cnt, 1)[:, None], c)
        out.history.append({"epoch": epoch, "score": g, "sse": max(total - g, 0.0), "distortion": max(total - g, 0.0) / n, "comparisons": n * k, "seconds": time.time() - began})
        out.assignments = labelled.select("id", "cluster")
        if before is not None and g <= before * (1 + 1e-12):
            break
        before = g
    return out


def _batch_share(fraction: float, iterations: int, coverage: str) -> float:
    if coverage not in ("iteration", "total"):
        raise ValueError(f"unknown coverage {coverage!r}")
    return fraction if coverage == "iteration" else fraction / iterations


def minibatch(rows: DataFrame, k: int, fraction: float = 0.10, iterations: int = 30, seed: int = 42, coverage: str = "iteration") -> ClusterResult:
    """Mini-batches drawn by hash; each moves its winners by the running 1/count rule in closed form: a centroid is the
    mean of all it has won so far. coverage: fraction is that of an iteration, or of all together."""
    rows = stored(_doubles(rows), "rows")
    d, part = dimension(rows), _batch_share(fraction, iterations, coverage)
    c = np.array(seeds(rows, k, "random", seed), np.float64)
    k = len(c)
    s, seen = np.zeros((k, d)), np.zeros(k)
    out = ClusterResult(rows, k)
    for i in range(iterations):
        began = time.time()
        batch = rows.where(portable_hash(F.col("id"), f"mb{seed}-{i}") < int(part * (1 << 28)))
        s2, cnt, _ = _state(nearest_labels(batch, c), k, d)
        s, seen = s + s2, seen + cnt
        c = np.where(seen[:, None] > 0, s / np.maximum(seen, 1)[:, None], c)
        out.history.append({"epoch": i + 1, "moves": int(cnt.sum()), "comparisons": int(cnt.sum()) * k, "seconds": time.time() - began})
    out.assignments = nearest_labels(rows, c).select("id", "cluster")
    return out


def minibatch_relational(rows: DataFrame, k: int, fraction: float = 0.10, iterations: int = 3, seed: int = 42) -> DataFrame:
    """The same in fixed point by joins and aggregates only: (id, cluster)."""
    top = rows.orderBy(portable_hash(F.col("id"), f"seed{seed}"), "id").limit(k).select("id", "vec")
    order = Window.orderBy(portable_hash(F.col("id"), f"seed{seed}"), "id")  # k rows
    first = cluster_state(top.withColumn("cluster", (F.row_number().over(order) - 1).cast("int")), True)
    won = None  # (id, vec, cluster) of all batches so far
    state = first
    for i in range(iterations):
        batch = rows.where(portable_hash(F.col("id"), f"mb{seed}-{i}") < int(fraction * (1 << 28))).select("id", "vec")
        own = batch.join(assign_nearest(batch, state, True).select("id", "cluster"), "id")
        won = stored(own if won is None else won.unionByName(own), "won")
        seen = cluster_state(won, True)
        state = seen.unionByName(first.join(seen, "cluster", "left_anti"))
    return assign_nearest(rows, state, True).select("id", "cluster")


def restarts(rows: DataFrame, method: str, k: int, runs: int = 10, by: str = "distortion", classes: DataFrame | None = None, seed: int = 1000) -> tuple[DataFrame, ClusterResult]:
    """Runs of a sequential method that differ by seed, each a task: their values (run, value), and the best run.

    by: distortion, or entropy against classes (id, cls). The rows are broadcast, so more than LOCAL_ROWS are refused.
    """
    if by not in ("distortion", "entropy") or (by == "entropy") != (classes is not None):
        raise ValueError("by is distortion, or entropy with classes")
    n = rows.count()
    if n > LOCAL_ROWS:
        raise ValueError(f"{n} rows are too many for one task ({LOCAL_ROWS})")
    spark = rows.sparkSession
    data = rows.select("id", "vec") if classes is None else rows.select("id", "vec").join(classes.select("id", "cls"), "id", "left")
    got = data.orderBy("id").toArrow()  # bounded above
    cls = None if classes is None else np.unique([str(x) if x is not None else "" for x in got["cls"].to_pylist()], return_inverse=True)
    known = None if classes is None else np.array([x is not None for x in got["cls"].to_pylist()])
    shared = spark.sparkContext.broadcast((_matrix(got["vec"].combine_chunks()), None if cls is None else cls[1], known))

    def each(frames):
        x, code, some = shared.value
        for f in frames:
            values = []
            for r in f["run"]:
                run = kernels.METHODS[method](x, k, seed + int(r))
                values.append(kernels.sse(x, run.labels, run.k) / len(x) if code is None else _entropy(run.labels[some], code[some]))
            yield f.assign(value=values)

    values = stored(spark.range(runs).select(F.col("id").cast("int").alias("run")).repartition(runs, "run").mapInPandas(each, "run int, value double"), "runs")
    best = values.orderBy("value", "run").first().run
    x = shared.value[0]
    run = kernels.METHODS[method](x, k, seed + best)
    labels = spark.createDataFrame(pa.table({"id": got["id"], "cluster": pa.array(run.labels.astype(np.int32))}))
    return values, ClusterResult(labels, run.k, run.history, run.nodes)


def _entropy(labels: np.ndarray, code: np.ndarray) -> float:
    kinds, code = np.unique(code, return_inverse=True)
    t = np.zeros((labels.max(initial=0) + 1, max(len(kinds), 1)))
    np.add.at(t, (labels, code), 1)
    t = t[t.sum(1) > 0]
    p = t / t.sum(1, keepdims=True)
    h = -(p * np.log(np.where(p > 0, p, 1))).sum(1)
    return float((t.sum(1) * h).sum() / max(t.sum(), 1) / np.log(max(len(kinds), 2)))
