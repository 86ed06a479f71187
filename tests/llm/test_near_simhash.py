"""The near-duplicate stage: SimHash links against brute force, and parities that leave out pairs before they are given out."""

import random

import numpy as np

from gainclust.llm import near_text
from gainclust.llm.components import components


def test_fingerprints_are_linked_before_any_other_search(spark):
    rnd = random.Random(8)
    base = [rnd.getrandbits(64) for _ in range(12)]
    fps = [f ^ sum(1 << b for b in rnd.sample(range(64), n)) for f in base for n in (0, 0, 1, 3, 4, 9)]
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    nodes = spark.createDataFrame([(i, f, [1]) for i, f in enumerate(signed)] + [(900, signed[0], []), (901, 0, [])], "node long, fp long, keys array<long>")
    links = near_text.alike(nodes)
    got = {(r.a, r.b) for r in links.collect()}
    assert all((fps[a] ^ fps[b]).bit_count() <= 3 and a < b for a, b in got)  # nothing beyond three bits, no empty set
    roots = {r.node: r.root for r in components(links).collect()}
    for i, f in enumerate(fps):
        for j in range(i):
            if (f ^ fps[j]).bit_count() <= 3:
                assert roots[i] == roots[j], (i, j)


def test_pairs_that_share_too_little_are_not_given_out(spark):
    """One group of near copies, most below 0.8: only a few more pairs than the similar ones come out, and all of these do."""
    rnd = np.random.default_rng(4)
    common = rnd.integers(0, 1 << 63, 80).astype(np.uint64)
    sets = [np.unique(np.concatenate([common[: rnd.integers(50, 81)], rnd.integers(0, 1 << 63, rnd.integers(5, 40)).astype(np.uint64)])) for _ in range(120)]
    marks = spark.createDataFrame([(i, near_text.parities(s).tolist()) for i, s in enumerate(sets)], "node long, marks array<long>")
    rows = spark.createDataFrame([(7, 0, 0, len(s), 0, i, i) for i, s in enumerate(sets)], "token long, before int, pos int, n int, fp long, node long, root long")
    like = lambda a, b: len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    similar = {(i, j) for j in range(120) for i in range(j) if like(sets[i], sets[j]) >= 0.8}
    every, few = ({(r.a, r.b) for r in near_text.across(rows, 0.8, None, m).collect()} for m in (None, marks))
    assert similar and similar <= few <= every
    assert len(every) > 3 * len(few) and len(few) < 1.5 * len(similar) + 50
