"""Sequential clustering of one array of rows in numpy: used inside partitions, groups, hierarchies and tests."""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np


@dataclass
class Run:
    labels: np.ndarray
    k: int
    history: list[dict] = field(default_factory=list)
    nodes: list[dict] = field(default_factory=list)
    fewer: dict[int, np.ndarray] = field(default_factory=dict)

    def centroids(self, x: np.ndarray) -> np.ndarray:
        s, cnt = sums(x, self.labels, self.k)
        return s / np.maximum(cnt, 1)[:, None]


def sums(x: np.ndarray, labels: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    cnt = np.bincount(labels, minlength=k).astype(np.float64)
    out = np.zeros((k, x.shape[1]))
    if x.shape[1] < 8 or len(x) < 4 * k:
        np.add.at(out, labels, x)
        return out, cnt
    for c in np.flatnonzero(cnt):  # in the same order, so with the same bits, and ten times faster on wide rows
        out[c] = x[np.flatnonzero(labels == c)].sum(0) if cnt[c] < len(x) else x.sum(0)
    return out, cnt


def sums_after(x: np.ndarray, s: np.ndarray, cnt: np.ndarray, old: np.ndarray | None, new: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sums by the new labels: where few rows have changed, from those by the old ones, which add up to s and cnt."""
    k = len(cnt)
    changed = None if old is None else np.flatnonzero(old != new)
    if changed is None or 8 * len(changed) > len(x):
        return sums(x, new, k)
    few = x[changed]
    (gained, more), (lost, fewer) = sums(few, new[changed], k), sums(few, old[changed], k)
    return s + gained - lost, cnt + more - fewer


def from_row(x: np.ndarray, i: int) -> np.ndarray:
    """Squared distances from row i, some rows at a time, as these fit the cache."""
    out = np.empty(len(x))
    for a in range(0, len(x), BLOCK):
        y = x[a : a + BLOCK] - x[i]
        y *= y
        out[a : a + BLOCK] = y.sum(1)
    return out


def score(s: np.ndarray, cnt: np.ndarray) -> float:
    return float(((s * s).sum(1)[cnt > 0] / cnt[cnt > 0]).sum())


def sse(x: np.ndarray, labels: np.ndarray, k: int) -> float:
    s, cnt = sums(x, labels, k)
    return max(float((x * x).sum()) - score(s, cnt), 0.0)


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    out = np.empty(len(x), np.int64)
    half = (c * c).sum(1)
    for a in range(0, len(x), 8192):
        out[a : a + 8192] = np.argmin(half - 2 * (x[a : a + 8192] @ c.T), axis=1)
    return out


def seeds_dsq(x: np.ndarray, k: int, rng: np.random.Generator) -> np.ndarray:
    """Rows with probability in proportion to the squared distance to the nearest seed (exponential race)."""
    rows = [int(rng.integers(len(x)))]
    d2 = from_row(x, rows[0])
    while len(rows) < k:
        race = np.where(d2 > 0, rng.exponential(size=len(x)) / np.maximum(d2, 1e-300), np.inf)
        i = int(np.argmin(race))
        if not np.isfinite(race[i]):  # every row equals a seed
            i = next(j for j in range(len(x)) if j not in set(rows))
        rows.append(i)
        d2 = np.minimum(d2, from_row(x, i))
    return np.array(rows)


def start(x: np.ndarray, k: int, init, rng: np.random.Generator) -> np.ndarray:
    if isinstance(init, np.ndarray):
        return init.astype(np.int64).copy()
    if init == "random_label":
        return rng.integers(k, size=len(x))
    if init == "seed_nearest":
        return nearest(x, x[rng.choice(len(x), k, replace=False)])
    if init == "dsq_nearest":
        return nearest(x, x[seeds_dsq(x, k, rng)])
    raise ValueError(f"unknown start {init!r}")


BLOCK = 128  # rows whose products are taken together
FRESH = 8  # epochs after which sums are taken from the data again, however few rows have moved
SCAN = 32  # clusters looked at together when the first improving one is taken


def one_pass(x: np.ndarray, xx: np.ndarray, labels: np.ndarray, s: np.ndarray, cnt: np.ndarray, order: np.ndarray, move: str, least: float, candidates: np.ndarray | None = None, rotate: int = 0, scan: str = "rotated", by_cluster: bool = False) -> tuple[int, int]:
    """Visit rows in order and move each by exact gains, state updated at once. Returns (moves, comparisons).

    candidates: clusters to test, per row or (by_cluster) per cluster that a row is in. scan: where first moves begin to look.
    """
    moved = compared = 0
    dd = (s * s).sum(1)
    with np.errstate(divide="ignore", invalid="ignore"):
        if candidates is None and (move == "best" or len(cnt) <= SCAN):
            for a in range(0, len(order), BLOCK):
                rows = order[a : a + BLOCK]
                begin = None if move == "best" else (rows * 2654435761 + rotate) % len(cnt) if scan == "rotated" else np.zeros(len(rows), np.int64)
                m, c = _block(x, xx, labels, s, cnt, dd, rows, least, begin)
                moved, compared = moved + m, compared + c
            return moved, compared
        for i in order:
            u = labels[i]
            if cnt[u] <= 1:
                continue
            who = None
            if candidates is not None:
                who = candidates[u if by_cluster else i]
                who = who[(who != u) & (who >= 0)]
            elif scan == "rotated":
                who = (np.arange(len(cnt)) + (int(i) * 2654435761 + rotate)) % len(cnt)
                who = who[who != u]
            else:
                who = np.delete(np.arange(len(cnt)), u)
            row, q = x[i], xx[i]
            pu = float(s[u] @ row)
            lost = (2 * pu - q - dd[u] / cnt[u]) / (cnt[u] - 1)
            v = -1
            for at in range(0, len(who), SCAN if move == "first" else max(len(who), 1)):
                part = who[at : at + SCAN] if move == "first" else who
                p = s[part] @ row
                gain = np.where(cnt[part] > 0, (2 * p + q - dd[part] / cnt[part]) / (cnt[part] + 1), q) - lost
                j = int(np.argmax(gain > least)) if move == "first" else int(np.argmax(gain))
                if gain[j] > least:
                    compared += j + 1 if move == "first" else len(part)
                    v, pv = int(part[j]), float(p[j])
                    break
                compared += len(part)
            if v < 0:
                continue
            dd[v] += 2 * pv + q
            dd[u] += q - 2 * pu
            s[v] += row
            s[u] -= row
            cnt[v] += 1
            cnt[u] -= 1
            labels[i] = v
            moved += 1
    return moved, compared


def _first(ok: np.ndarray, begin: int, own: int) -> tuple[int, int]:
    """The first cluster that is ok, from begin on and round, and how many others were looked at up to it."""
    k = len(ok)
    away = (np.flatnonzero(ok) - begin) % k
    v = int(away.min())
    return (begin + v) % k, v + 1 - ((own - begin) % k < v)


def _block(x: np.ndarray, xx: np.ndarray, labels: np.ndarray, s: np.ndarray, cnt: np.ndarray, dd: np.ndarray, rows: np.ndarray, least: float, begin: np.ndarray | None) -> tuple[int, int]:
    """The rows one after the other, as if each were looked at alone: products of all are taken at once, and after a
    move only what its two clusters change is taken again. begin: where first moves begin to look, row by row (of SCAN
    clusters at most)."""
    y, q, own = x[rows], xx[rows], labels[rows]
    n, k = len(rows), len(cnt)
    p = y @ s.T
    if k <= SCAN:
        return _small_block(y, q, own, labels, s, cnt, dd, rows, least, p, begin)
    won = np.where(cnt > 0, (2 * p + q[:, None] - dd / cnt) / (cnt + 1), q[:, None])
    at = np.arange(n)
    won[at, own] = -np.inf
    lost = np.where(cnt[own] > 1, (2 * p[at, own] - q - dd[own] / cnt[own]) / (cnt[own] - 1), np.inf)
    best = won.argmax(1)
    top = won[at, best]
    if 8 * np.count_nonzero(top - lost > least) > n:
        return _dense_block(y, q, own, labels, s, cnt, dd, rows, least, 2 * p, begin)
    i = moved = 0
    alone = 0
    while True:
        hit = top[i:] - lost[i:] > least
        j = int(hit.argmax()) if i < n else 0
        end = i + j if i < n and hit[j] else n
        alone += int((cnt[own[i:end]] <= 1).sum())  # these are passed over
        if end == n:
            break
        i = end
        u, v = int(own[i]), int(best[i])
        dd[v] += 2 * p[i, v] + q[i]
        dd[u] += q[i] - 2 * p[i, u]
        s[v] += y[i]
        s[u] -= y[i]
        cnt[v] += 1
        cnt[u] -= 1
        labels[rows[i]] = v
        moved += 1
        r = slice(i + 1, n)
        if i + 1 < n:
            inner = y[r] @ y[i]  # few rows move, so the products of all pairs are not taken
            p[r, v] += inner
            p[r, u] -= inner
            o, z, b, t = own[r], q[r], best[r], top[r]
            for c in (u, v):
                w = (2 * p[r, c] + z - dd[c] / cnt[c]) / (cnt[c] + 1) if cnt[c] > 0 else z.copy()
                w[o == c] = -np.inf
                won[r, c] = w
                up = (w > t) | ((w == t) & (c < b) & (w > -np.inf))
                b[up], t[up] = c, w[up]
            again = np.flatnonzero((b == u) | (b == v))
            if len(again):
                b[again] = won[r][again].argmax(1)
                t[again] = won[r][again, b[again]]
            mine = np.flatnonzero((o == u) | (o == v))
            if len(mine):
                c = o[mine]
                lost[i + 1 + mine] = np.where(cnt[c] > 1, (2 * p[i + 1 + mine, c] - z[mine] - dd[c] / cnt[c]) / (cnt[c] - 1), np.inf)
        i += 1
    return moved, (n - alone) * (k - 1)


def _small_block(y: np.ndarray, q: np.ndarray, own: np.ndarray, labels: np.ndarray, s: np.ndarray, cnt: np.ndarray, dd: np.ndarray, rows: np.ndarray, least: float, p: np.ndarray, begin: np.ndarray | None) -> tuple[int, int]:
    """The same for few clusters: after a move the gains of all rows that follow are taken again."""
    n, k = len(rows), len(cnt)
    p *= 2
    mean, more = np.where(cnt > 0, dd / cnt, 0.0), cnt + 1
    i = moved = alone = spared = 0
    while i < n:
        z, o, at = q[i:], own[i:], np.arange(n - i)
        won = p[i:] + z[:, None]
        won -= mean
        won /= more
        mine = p[i:][at, o]
        mine -= z
        mine -= mean[o]
        left = (cnt - 1)[o]
        lost = np.where(left > 0, mine / left, np.inf)
        won[at, o] = -np.inf
        best = won.argmax(1)
        hit = won[at, best] - lost > least
        if not moved and 4 * np.count_nonzero(hit) > n:
            return _dense_block(y, q, own, labels, s, cnt, dd, rows, least, p, begin)
        j = int(hit.argmax())
        if not hit[j]:
            return moved, (n - alone - int(np.count_nonzero(left <= 0))) * (k - 1) - spared
        alone += int(np.count_nonzero(left[:j] <= 0))  # these are passed over
        u, v = int(o[j]), int(best[j])
        if begin is not None:
            v, seen = _first(won[j] - lost[j] > least, int(begin[i + j]), u)
            spared += k - 1 - seen
        i += j
        _move(y[i], float(q[i]), u, v, float(p[i, u]), float(p[i, v]), s, cnt, dd, mean, more)
        labels[rows[i]] = v
        moved += 1
        i += 1
        inner = y[i:] @ y[i - 1]  # few rows move, so the products of all pairs are not taken
        inner *= 2
        p[i:, v] += inner
        p[i:, u] -= inner
    return moved, (n - alone) * (k - 1) - spared


def _move(row: np.ndarray, z: float, u: int, v: int, pu: float, pv: float, s: np.ndarray, cnt: np.ndarray, dd: np.ndarray, mean: np.ndarray, more: np.ndarray) -> None:
    """A row of squared length z goes from u to v; pu, pv are twice its products with their sums."""
    dd[v] += pv + z
    dd[u] += z - pu
    s[v] += row
    s[u] -= row
    cnt[v] += 1
    cnt[u] -= 1
    mean[v], mean[u], more[v], more[u] = dd[v] / cnt[v], dd[u] / cnt[u], cnt[v] + 1, cnt[u] + 1


def _dense_block(y: np.ndarray, q: np.ndarray, own: np.ndarray, labels: np.ndarray, s: np.ndarray, cnt: np.ndarray, dd: np.ndarray, rows: np.ndarray, least: float, p: np.ndarray, begin: np.ndarray | None = None) -> tuple[int, int]:
    """The same where many rows move: row by row, with the products (twice, as p) kept up to date."""
    inner = y @ y.T
    inner *= 2
    mean, more = np.where(cnt > 0, dd / cnt, 0.0), cnt + 1
    moved = alone = spared = 0
    for i, (u, z, row) in enumerate(zip(own.tolist(), q.tolist(), p)):
        if cnt[u] <= 1:
            alone += 1
            continue
        gain = row + z
        gain -= mean
        gain /= more
        gain[u] = -np.inf
        v = int(gain.argmax())
        lost = (row[u] - z - mean[u]) / (cnt[u] - 1)
        if not gain[v] - lost > least:
            continue
        if begin is not None:
            v, seen = _first(gain - lost > least, int(begin[i]), u)
            spared += len(cnt) - 1 - seen
        _move(y[i], z, u, v, float(row[u]), float(row[v]), s, cnt, dd, mean, more)
        p[i + 1 :, v] += inner[i + 1 :, i]
        p[i + 1 :, u] -= inner[i + 1 :, i]
        labels[rows[i]] = v
        moved += 1
    return moved, (len(rows) - alone) * (len(cnt) - 1) - spared


def nearest_by_gain(x: np.ndarray, s: np.ndarray, cnt: np.ndarray, k0: int) -> np.ndarray:
    """Per row the k0 clusters it would win most in, ties to the lower; its own counts like any other."""
    with np.errstate(divide="ignore", invalid="ignore"):
        q = (x * x).sum(1)[:, None]
        won = np.where(cnt > 0, (2 * (x @ s.T) + q - (s * s).sum(1) / cnt) / (cnt + 1), -np.inf)
    return np.argsort(-won, axis=1, kind="stable")[:, :k0]


def nearest_centroids(s: np.ndarray, cnt: np.ndarray, k0: int) -> np.ndarray:
    """Per cluster the k0 others of nearest centroid; -1 where there are fewer."""
    c = s / np.maximum(cnt, 1)[:, None]
    half = (c * c).sum(1)
    d2 = half[:, None] + half - 2 * c @ c.T
    d2[:, cnt == 0] = np.inf
    np.fill_diagonal(d2, np.inf)
    near = np.argsort(d2, axis=1, kind="stable")[:, :k0]
    return np.where(np.isfinite(np.take_along_axis(d2, near, 1)), near, -1)


CANDIDATES = ("row", "cluster")


def gain_kway(x: np.ndarray, k: int, init="random_label", move: str = "best", max_epochs: int = 20, tol: float = 0.0, seed: int = 42, candidates: int | None = None, warm_epochs: int = 3, candidate_mode: str = "row", scan: str = "rotated", min_move_ratio: float = 0.0) -> Run:
    """Moves by score gain until an epoch moves no more than min_move_ratio of the rows.

    candidates: after warm_epochs only k0 clusters are tested, those a row would win most in (candidate_mode row, taken
    once) or those of the centroids nearest to its cluster's (cluster, taken every epoch); what that takes is counted.
    """
    if move not in ("best", "first") or candidate_mode not in CANDIDATES or scan not in ("rotated", "ascending"):
        raise ValueError(f"unknown move {move!r}, candidate mode {candidate_mode!r} or scan {scan!r}")
    if not 1 <= k <= max(len(x), 1):
        raise ValueError(f"k = {k} of {len(x)} rows")
    rng = np.random.default_rng(seed)
    labels = start(x, k, init, rng)
    xx = (x * x).sum(1)
    total, run = float(xx.sum()), Run(labels, k)
    least = 1e-12 * total / max(len(x), 1)
    near = None
    s, cnt = sums(x, labels, k)
    before = score(s, cnt)
    for epoch in range(1, max_epochs + 1):
        extra = 0
        if candidates and epoch > warm_epochs and candidates < k:
            if candidate_mode == "cluster":
                near, extra = nearest_centroids(s, cnt, candidates), k * (k - 1)
            elif near is None:
                near, extra = nearest_by_gain(x, s, cnt, candidates), len(x) * k
        moved, compared = one_pass(x, xx, labels, s, cnt, rng.permutation(len(x)), move, least, near, epoch, scan, candidate_mode == "cluster")
        if 8 * moved > len(x) or epoch % FRESH == 0:
            s, cnt = sums(x, labels, k)  # from the data again: no drift
        after = score(s, cnt)
        run.history.append({"epoch": epoch, "moves": moved, "score": after, "sse": max(total - after, 0.0), "distortion": max(total - after, 0.0) / max(len(x), 1), "comparisons": compared + extra})
        if moved <= min_move_ratio * len(x) or (tol and after - before <= tol * abs(before)):
            break
        before = after
    return run


def lloyd(x: np.ndarray, k: int, seeding: str = "random", max_epochs: int = 130, seed: int = 42) -> Run:
    if not 1 <= k <= max(len(x), 1):
        raise ValueError(f"k = {k} of {len(x)} rows")
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=False)] if seeding == "random" else x[seeds_dsq(x, k, rng)]
    run, labels, s, cnt = Run(np.zeros(len(x), np.int64), k), None, np.zeros((k, x.shape[1])), np.zeros(k)
    total = float((x * x).sum())
    for epoch in range(1, max_epochs + 1):
        new = nearest(x, c)
        moved = len(x) if labels is None else int((new != labels).sum())
        s, cnt = sums_after(x, s, cnt, labels if epoch % FRESH else None, new)
        labels = new
        c = np.where(cnt[:, None] > 0, s / np.maximum(cnt, 1)[:, None], c)
        now = max(total - score(s, cnt), 0.0)
        run.history.append({"epoch": epoch, "moves": moved, "score": total - now, "sse": now, "distortion": now / max(len(x), 1), "comparisons": len(x) * k})
        if not moved:
            break
    run.labels = labels
    return run


def minibatch(x: np.ndarray, k: int, fraction: float = 0.10, iterations: int = 30, seed: int = 42, brief: bool = False) -> Run:
    """brief: labels and distortion of the last iteration only."""
    rng = np.random.default_rng(seed)
    c, seen = x[rng.choice(len(x), k, replace=False)].copy(), np.zeros(k)
    run, size = Run(np.zeros(len(x), np.int64), k), max(1, int(len(x) * fraction))
    for epoch in range(1, iterations + 1):
        batch = x[rng.choice(len(x), size, replace=False)]
        s, cnt = sums(batch, nearest(batch, c), k)
        hit = cnt > 0
        c[hit] = (seen[hit, None] * c[hit] + s[hit]) / (seen + cnt)[hit, None]
        seen += cnt
        if brief and epoch < iterations:
            continue
        run.labels = nearest(x, c)
        now = sse(x, run.labels, k)
        run.history.append({"epoch": epoch, "moves": size, "score": 0.0, "sse": now, "distortion": now / len(x), "comparisons": size * k})
    return run


def lvq_rate(iteration: int, rate0: float = 0.01, decay: float = 4e-4) -> float:
    return max(rate0 - decay * iteration, 0.0)


def online_lvq(x: np.ndarray, k: int, rate0: float = 0.01, decay: float = 4e-4, iterations: int = 30, seed: int = 42) -> Run:
    rng = np.random.default_rng(seed)
    c, run = x[rng.choice(len(x), k, replace=False)].copy(), Run(np.zeros(len(x), np.int64), k)
    for epoch in range(iterations):
        if (rate := lvq_rate(epoch, rate0, decay)) > 0:
            for i in rng.permutation(len(x)):
                j = int(np.argmin(((c - x[i]) ** 2).sum(1)))
                c[j] += rate * (x[i] - c[j])
        run.labels = nearest(x, c)
        now = sse(x, run.labels, k)
        run.history.append({"epoch": epoch + 1, "moves": len(x), "score": 0.0, "sse": now, "distortion": now / len(x), "comparisons": len(x) * k})
    return run


LVQ_BLOCK = 32  # rows whose products are taken together


def online_lvq_many(x: np.ndarray, runs: list[tuple[int, int]], rate0: float = 0.01, decay: float = 4e-4, iterations: int = 30) -> list[np.ndarray]:
    """Labels of online_lvq for every (k, seed) of runs, all of which go through their rows in step.

    The products of a block's rows with centroids and with each other are taken at once; what a row changes in those of
    the rows after it follows from them, so each run visits its rows one after the other as if alone.
    """
    (n, d), most, r = x.shape, max(k for k, _ in runs), len(runs)
    rngs = [np.random.default_rng(seed) for _, seed in runs]
    c, at = np.zeros((r, most, d)), np.arange(r)
    for j, (k, _) in enumerate(runs):
        c[j, :k] = x[rngs[j].choice(n, k, replace=False)]
    xx, ends = (x * x).sum(1), [0] + [j for j in range(1, r) if runs[j][0] != runs[j - 1][0]] + [r]
    parts = [(slice(a, b), runs[a][0]) for a, b in zip(ends, ends[1:])]
    for epoch in range(iterations):
        if not (rate := lvq_rate(epoch, rate0, decay)) > 0:
            continue
        order, keep = np.stack([g.permutation(n) for g in rngs]), 1 - rate
        for a in range(0, n, LVQ_BLOCK):
            rows = order[:, a : a + LVQ_BLOCK]
            y, b = x[rows], rows.shape[1]
            turned, by, half = y.transpose(0, 2, 1), np.zeros((r, most, b)), np.full((r, most), np.inf)
            for g, k in parts:
                by[g, :k] = c[g, :k] @ turned[g]
                half[g, :k] = np.einsum("rkd,rkd->rk", c[g, :k], c[g, :k]) / 2
            p, flat, inner = by.reshape(r * most, b), half.reshape(-1), rate * (y @ turned)
            own, z = np.empty((r, b), np.int64), rate * rate / 2 * xx[rows]
            for i in range(b):
                away = half - by[:, :, i]
                own[:, i] = j = (away <= away.min(1, keepdims=True) + 1e-13).argmax(1)  # equal centroids: the first
                j = at * most + j
                mine = p[j]
                flat[j] = keep * keep * flat[j] + rate * keep * mine[:, i] + z[:, i]
                mine *= keep
                mine += inner[:, i]
                p[j] = mine
            later = np.triu(own[:, :, None] == own[:, None, :], 1).sum(2)  # how often the row's centroid moves on after it
            won = own[:, None, :] == np.arange(most)[:, None]
            w, stay = np.where(won, (rate * keep**later)[:, None, :], 0.0), (keep ** won.sum(2))[:, :, None]
            for g, k in parts:
                c[g, :k] *= stay[g, :k]
                c[g, :k] += w[g, :k] @ y[g]
    return [nearest(x, c[j, :k]) for j, (k, _) in enumerate(runs)]


def _node_seed(seed: int, node: str) -> int:
    import hashlib

    return int.from_bytes(hashlib.md5(f"{seed}:{node}".encode()).digest()[:6], "big")


PRIORITIES = ("size", "avg_pair")


def hierarchy(x: np.ndarray, k: int, splitter: str = "gain", init: str = "random_label", s: int = 2, priority: str = "size", seed: int = 42, move: str = "best", max_epochs: int = 200, root: str = "0", least: float = 0, also: tuple[int, ...] = ()) -> Run:
    """Split the first leaf of the queue into s parts until k leaves stand. A split depends on its rows and node id only.

    least: leaves of fewer rows are not split (for parts of a larger hierarchy). also: fewer numbers of leaves to give the
    labels of as well (Run.fewer); of two parts each, splits do not depend on k.
    """
    if also and s > 2:
        raise ValueError("fewer leaves are given for splits in two only")
    if move == "first":
        raise ValueError("first moves are for the flat method")
    if s < 2 or not 1 <= k <= max(len(x), 1) or priority not in PRIORITIES or splitter not in ("gain", "lloyd"):
        raise ValueError(f"s = {s}, k = {k} of {len(x)} rows, priority {priority!r}, splitter {splitter!r}")
    leaves = {0: (root, np.arange(len(x)))}
    run, compared, per_pass, rank, number = Run(np.full(len(x), 0), k), 0, 0, 0, 1
    queue: list = []

    def push(n: int) -> None:
        node, rows = leaves[n]
        y = x[rows]
        err = sse(y, np.zeros(len(rows), np.int64), 1)
        loose = 2 * len(rows) * err / (len(rows) * (len(rows) - 1)) if len(rows) > 1 else 0.0
        run.nodes.append({"node_id": node, "parent": node.rpartition(".")[0] or None, "depth": node.count("."), "cnt": len(rows), "sse": err, "split_rank": None, "is_leaf": True})
        if len(rows) > 1 and len(rows) >= least and err > 1e-12 * max(float((y * y).sum()), 1e-300):
            heapq.heappush(queue, (-(len(rows) if priority == "size" else loose), node, n, len(run.nodes) - 1))

    push(0)
    def named() -> np.ndarray:
        out = np.zeros(len(x), np.int64)
        for label, (_, rows) in enumerate(leaves.values()):
            out[rows] = label
        return out

    while len(leaves) < k and queue:
        if len(leaves) in also:
            run.fewer[len(leaves)] = named()
        _, node, n, at = heapq.heappop(queue)
        rows = leaves[n][1]
        parts = min(s, k - len(leaves) + 1, len(rows))
        own = _node_seed(seed, node)
        if splitter == "gain":
            got = gain_kway(x[rows], parts, init, "best", max_epochs, seed=own)
        else:
            got = lloyd(x[rows], parts, "dsq" if init == "dsq_nearest" else "random", max_epochs, own)
        compared += sum(h["comparisons"] for h in got.history)
        per_pass += len(rows) * (parts - 1)  # what one pass over each split node costs
        present = np.unique(got.labels)
        if len(present) < 2:
            continue
        del leaves[n]
        rank += 1
        run.nodes[at] |= {"split_rank": rank, "is_leaf": False}
        for part in present:
            leaves[number] = (f"{node}.{part}", rows[got.labels == part])
            push(number)
            number += 1
    run.labels = names = named()
    run.fewer |= {fewer: names for fewer in also if fewer >= len(leaves)}
    now = sse(x, names, k)
    run.history.append({"epoch": 1, "moves": len(x), "score": float((x * x).sum()) - now, "sse": now, "distortion": now / max(len(x), 1), "comparisons": compared, "per_pass": per_pass})
    return run


def unit_rows(x: np.ndarray) -> np.ndarray:
    n = np.sqrt((x * x).sum(1, keepdims=True))
    return np.where(np.abs(n - 1) < 1e-6, x, x / np.where(n > 0, n, 1))


#: Every method of the comparison by name: rows, clusters, seed -> Run.
METHODS = {
    "lloyd": lambda x, k, seed: lloyd(x, k, "random", 30, seed),
    "lloyd_dsq": lambda x, k, seed: lloyd(x, k, "dsq", 30, seed),
    "minibatch": lambda x, k, seed: minibatch(x, k, seed=seed),
    "online_lvq": lambda x, k, seed: online_lvq(x, k, seed=seed),
    "gain_random_label": lambda x, k, seed: gain_kway(x, k, "random_label", seed=seed),
    "gain_seed_nearest": lambda x, k, seed: gain_kway(x, k, "seed_nearest", seed=seed),
    "gain_dsq_nearest": lambda x, k, seed: gain_kway(x, k, "dsq_nearest", seed=seed),
    "gain_random_label_first": lambda x, k, seed: gain_kway(x, k, "random_label", "first", seed=seed),
    "gain_seed_nearest_first": lambda x, k, seed: gain_kway(x, k, "seed_nearest", "first", seed=seed),
    "gain_dsq_nearest_first": lambda x, k, seed: gain_kway(x, k, "dsq_nearest", "first", seed=seed),
    "bisect_lloyd": lambda x, k, seed: hierarchy(x, k, "lloyd", "seed_nearest", seed=seed),
    "bisect_lloyd_dsq": lambda x, k, seed: hierarchy(x, k, "lloyd", "dsq_nearest", seed=seed),
    "gain_bisect_random_label": lambda x, k, seed: hierarchy(x, k, "gain", "random_label", seed=seed),
    "gain_bisect_seed_nearest": lambda x, k, seed: hierarchy(x, k, "gain", "seed_nearest", seed=seed),
    "gain_bisect_dsq_nearest": lambda x, k, seed: hierarchy(x, k, "gain", "dsq_nearest", seed=seed),
    "cosine_bisect": lambda x, k, seed: hierarchy(unit_rows(x), k, "gain", "seed_nearest", seed=seed),
}
FLAT = [m for m in METHODS if "bisect" not in m]
HIERARCHIES = [m for m in METHODS if "bisect" in m]
#: Hierarchies by splitter and start; cosine_bisect takes rows of unit length.
SPLITS = {
    "bisect_lloyd": ("lloyd", "seed_nearest"),
    "bisect_lloyd_dsq": ("lloyd", "dsq_nearest"),
    "gain_bisect_random_label": ("gain", "random_label"),
    "gain_bisect_seed_nearest": ("gain", "seed_nearest"),
    "gain_bisect_dsq_nearest": ("gain", "dsq_nearest"),
    "cosine_bisect": ("gain", "seed_nearest"),
}


def labels_of(method: str, x: np.ndarray, ks: list[int], seeds: list[int]) -> Iterator[tuple[int, int, np.ndarray]]:
    """(k, seed, labels) of METHODS[method] for every k and seed. A hierarchy is grown once a seed, for the largest k:
    it passes through the smaller ones. Runs of online_lvq go in step, minibatch keeps no history."""
    if method in SPLITS:
        rows = unit_rows(x) if method == "cosine_bisect" else x
        for seed in seeds:
            run = hierarchy(rows, max(ks), *SPLITS[method], seed=seed, also=tuple(ks))
            yield from ((k, seed, run.fewer[k]) for k in ks)
    elif method == "online_lvq":
        runs = [(k, seed) for k in ks for seed in seeds]
        yield from ((*run, labels) for run, labels in zip(runs, online_lvq_many(x, runs)))
    else:
        one = METHODS[method] if method != "minibatch" else lambda x, k, seed: minibatch(x, k, seed=seed, brief=True)
        yield from ((k, seed, one(x, k, seed).labels) for k in ks for seed in seeds)
