"""Stages of the pipeline against brute force, with null and repeated ids."""

import random

import pytest

import corpus_pipeline
from gainclust.llm import near_text
from pyspark.sql import functions as F

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def table(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOCS).repartition(3)


def prose(rnd, n):
    return " ".join("".join(rnd.choices("abcdefghij", k=rnd.randint(2, 8))) for _ in range(n))


def test_near_duplicates_keep_rows_of_null_and_repeated_ids(spark):
    rnd = random.Random(5)
    alone = [prose(rnd, 120) for _ in range(6)]
    twice = prose(rnd, 120)
    rows = [(None, alone[0]), (None, alone[1]), (7, alone[2]), (7, alone[3]), (8, alone[4]), (None, twice), (7, twice), (3, twice), (3, twice), (8, alone[5])]
    got = corpus_pipeline.near_duplicates(spark, table(spark, rows), "").collect()
    key = lambda x: (x[0] is None, x[0] or 0, x[1])
    want = [(i, t) for i, t in rows if t != twice] + [(3, twice)]
    assert sorted(((r.doc_id, r.text) for r in got), key=key) == sorted(want, key=key)


def brute_components(texts, each=5, least=0.8):
    """Number of the component of every text, all pairs compared on their word shingles."""
    sets = []
    for t in texts:
        w = (t or "").lower().split()
        sets.append({tuple(w[i : i + each]) for i in range(max(len(w) - each + 1, 1))} if w else set())
    parent = list(range(len(texts)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            if sets[i] == sets[j] or len(sets[i] & sets[j]) >= least * len(sets[i] | sets[j]):
                parent[find(i)] = find(j)
    return [find(i) for i in range(len(texts))]


def changed(rnd, text, n):
    w = text.split()
    for at in rnd.sample(range(len(w)), n):
        w[at] = "new" + str(rnd.randrange(1000))
    return " ".join(w)


def test_near_duplicates_equal_brute_force(spark):
    """Copies on both sides of 0.8, a chain, and a group larger than the first round's range."""
    rnd = random.Random(6)
    texts = [None, "", "  ", "one", "one two", "ONE two"]
    for n in (1, 2, 3, 4, 5, 6, 8, 12):
        for _ in range(3):
            base = prose(rnd, 200)
            texts += [base, changed(rnd, base, n)]
    base = prose(rnd, 150)
    texts += [changed(rnd, base, rnd.randint(1, 4)) for _ in range(40)]
    link = prose(rnd, 200)
    for _ in range(6):
        texts.append(link)
        link = changed(rnd, link, 3)
    rows = [(None if i % 7 == 0 else i % 50, t) for i, t in enumerate(texts)]
    got = corpus_pipeline.near_duplicates(spark, table(spark, rows), "").collect()
    group = brute_components(texts)
    of = dict(zip(texts, group))
    assert sorted(of[r.text] for r in got) == sorted(set(group))


@pytest.mark.parametrize("small, block, first", [(2, 10_000, 2), (64, 8, None)])
def test_groups_row_by_row_and_in_blocks(spark, monkeypatch, small, block, first):
    """Pairs of different components of one prefix shingle, however the group is dealt."""
    monkeypatch.setattr(near_text, "SMALL", small)
    monkeypatch.setattr(near_text, "BLOCK", block)
    rows = [(t, 0, 50, 1 << (i % 5), 100 * t + i, 100 * t + i % 7, 0) for t in range(3) for i in range(40)] + [(9, 0, 50, 1, i, 0, 0) for i in range(30)]
    df = spark.createDataFrame(rows, "token long, pos int, n int, fp long, node long, root long, before int").repartition(3)
    got = near_text.across(df, 0.8, first).collect()
    want = {(a[4], b[4]) for a in rows for b in rows if a[0] == b[0] and a[4] < b[4] and a[5] != b[5]}
    pairs = {(r.a, r.b) for r in got}
    if first:
        assert pairs < want and any(r.more for r in got)
    else:
        assert pairs == want and not any(r.more for r in got)


def test_passages_of_over_50_words_go_and_shorter_ones_stay(spark):
    rnd = random.Random(9)
    long, short = prose(rnd, 60), prose(rnd, 45)
    own = [prose(rnd, 80) for _ in range(6)]
    texts = [f"{own[0]} {long} {own[1]}", f"{own[2]} {long}", f"{own[3]} {short}", f"{short} {own[4]}", own[5], None, ""]
    got = {r.doc_id: r.text for r in corpus_pipeline.repeats(spark, table(spark, list(enumerate(texts))), "").collect()}
    assert set(got) == {0, 1, 2, 3, 4}
    assert [long in got[i] for i in (0, 1)] == [False, False] and got[0].startswith(own[0]) and got[0].endswith(own[1])
    assert [got[i] for i in (2, 3, 4)] == texts[2:5]


def test_stages_on_an_empty_table(spark, sf):
    docs = table(spark, []).select("doc_id", "text", "lang", "source", "n_chars", F.lit(1).alias("id"), F.lit("x").alias("k"))
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
        assert docs.collect() == [], name


def test_stages_on_nulls_repeated_rows_and_clashing_columns(spark, sf):
    rnd = random.Random(3)
    rows = [(1, "the quick brown fox jumps over the lazy dog " * 3), (1, prose(rnd, 30)), (None, None), (None, ""), (2, "x"), (2, "x"), (3, "\U0001f642 " * 40)]
    docs = table(spark, rows).withColumns({"id": F.lit(7), "row": F.lit(1), "size": F.lit("s")})
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
        if name != "BPE encoding":
            assert docs.columns[:5] and set(corpus_pipeline.COLUMNS) <= set(docs.columns), name
        docs.collect()
