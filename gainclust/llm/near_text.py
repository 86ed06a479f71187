"""Near-duplicates by SimHash and by the true similarity of word shingles: fingerprints and sketches find candidates, sets decide.

A text is the set of its distinct shingle hashes; rows with equal sets are one node, and pairs are linked if their sets
have a Jaccard similarity of ``similarity`` or more.

1. Fingerprints of 64 bits that differ in BITS bits or fewer are linked by the search of ``simhash``, all of them; the
   exact check follows. Of the pairs of 0.8 or a little more these are few (they differ in about 10 bits), so the next
   steps find the others.
2. Nodes that share one of BANDS keys, each of EACH least values, are members. At 0.8 exactly a pair shares no key
   with a probability of (1 - 0.8^4)^20 = 0.00003; only members and linked nodes go on.
3. Members are joined exactly, by prefixes: with the shingles of every set in one common order, two sets similar
   enough share one of their first n - ceil(similarity * n) + 1, at places that still allow the overlap. The order is
   from rare to common by counts in a table of fixed size, so shingles of a common template seldom are in a prefix.
4. Candidates are verified on the sets. A first round takes near places only and merges most; later ones take every
   pair of different components that is left. A prefix shingle of over BLOCK members is dealt out in pairs of blocks.
   Parities of the set by hash (``marks``) bound from below how many shingles two sets do not share, so most pairs that
   are not similar enough are never given out.

Cases: wordless and null texts - the empty set, one node, linked to nothing else; fewer words than a shingle - the
whole sequence is the only shingle; whole texts are used; empty table - no rows; columns beside id and text are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainclust.llm.common import discard, shuffle_width, stored, trimmed
from gainclust.llm.components import components
from gainclust.llm.simhash import variant_links
from gainclust.llm.windows import PrefixHash, mixed

BANDS, EACH, FAR = 20, 4, 28  # FAR: fingerprints of similar sets differ in about 10 bits of 64
BITS, MARKS = 3, 8  # MARKS: longs of parities of a set
SLICE = 1 << 14  # shingles sketched together
LOT = 1 << 18  # bytes of text hashed together
WANTED = 2_000_000  # ids in a broadcast; more are joined by a shuffle
BUCKETS = 1 << 19  # counters of shingles; broadcast
GAPS, SMALL, BLOCK, FIRST = 8, 64, 8192, 4
_RANDOM = np.random.default_rng(42)
_TIMES = _RANDOM.integers(0, 1 << 32, (BANDS * EACH, 1), np.uint32) | np.uint32(1)
_PLUS = _RANDOM.integers(0, 1 << 32, (BANDS * EACH, 1), np.uint32)


def shingle_sets(texts: list[str | None], words_each: int) -> Iterator[np.ndarray]:
    """Per text its distinct shingle hashes, ascending."""
    at = 0
    while at < len(texts):
        words: list[bytes] = []
        counts: list[int] = []
        size = 0
        while at < len(texts) and size < LOT:
            own = (texts[at] or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: only A-Z change, only ASCII white space splits
            words += own
            counts.append(len(own))
            size += len(texts[at] or "") + 1
            at += 1
        if not words:
            yield from (np.empty(0, np.uint64) for _ in counts)
            continue
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = np.concatenate([[0], ends[:-1] + 1])
        prefix = PrefixHash(np.frombuffer(b" ".join(words), np.uint8))
        n = np.array(counts)
        shingles = np.where(n > 0, np.maximum(n - words_each + 1, 1), 0)
        base = np.cumsum(n) - n
        edge = np.cumsum(shingles)
        first = np.arange(edge[-1]) - np.repeat(edge - shingles, shingles) + np.repeat(base, shingles)
        last = np.minimum(first + words_each, np.repeat(base + n, shingles)) - 1
        hashes = mixed(prefix.of(starts[first], ends[last]))
        for a, b in zip((edge - shingles).tolist(), edge.tolist()):
            yield np.unique(hashes[a:b])


def sketch(hashes: np.ndarray) -> tuple[int, list[int]]:
    """Fingerprint and band keys of a set that is not empty."""
    ones, least = np.zeros(64, np.int64), np.full(BANDS * EACH, 0xFFFFFFFF, np.uint32)
    for a in range(0, len(hashes), SLICE):
        part = hashes[a : a + SLICE]
        ones += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        np.minimum(least, (part.astype(np.uint32) * _TIMES + _PLUS).min(1), out=least)
    fp = np.packbits(2 * ones > len(hashes), bitorder="little").view("<i8")[0]
    raw = least.astype("<u4").tobytes()
    keys = [xxhash.xxh64_intdigest(raw[4 * EACH * b : 4 * EACH * (b + 1)], b) for b in range(BANDS)]
    return int(fp), keys


def prints(docs: DataFrame, words_each: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (id, digest, n, fp, keys); equal digests are equal sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                digests, sizes, fps, keys = [], [], [], []
                for h in shingle_sets(part.column(1).to_pylist(), words_each):
                    fp, key = sketch(h) if len(h) else (0, [])
                    digests.append(blake2b(h.astype("<u8").tobytes(), digest_size=16).digest())
                    sizes.append(len(h))
                    fps.append(fp)
                    keys.append(np.array(key, np.uint64).view(np.int64))
                columns = [part.column(0), pa.array(digests, pa.binary()), pa.array(sizes, pa.int32()), pa.array(fps, pa.int64()), pa.array(keys, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(columns, names=["id", "digest", "n", "fp", "keys"])

    data = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return data.mapInArrow(trimmed(run), "id long, digest binary, n int, fp long, keys array<long>")


def alike(nodes: DataFrame, bits: int = BITS) -> DataFrame:
    """SimHash links (a, b) between nodes (node, fp, keys): the nodes of each fingerprint to its least one, and the least
    ones of linked fingerprints. The sets decide afterwards."""
    rows = nodes.where("size(keys) > 0")
    least = stored(rows.groupBy("fp").agg(F.min("node").alias("least")), "fingerprints")
    same = rows.join(least, "fp").where("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b"))
    links = variant_links(least.select("fp"), bits).toDF("x", "y")
    end = lambda fp, name: least.select(F.col("fp").alias(fp), F.col("least").alias(name))
    near = links.join(end("x", "p"), "x").join(end("y", "q"), "y").select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"))
    out = stored(same.unionByName(near).distinct(), "alike")
    discard(least)
    return out


def members(nodes: DataFrame) -> DataFrame:
    """Distinct nodes (node, fp) that share a key with another."""
    rows = nodes.select(F.explode("keys").alias("key"), "node", "fp")
    shared = rows.groupBy("key").agg(F.count(F.lit(1)).alias("nodes")).where("nodes > 1").select("key")
    return rows.join(shared, "key", "left_semi").select("node", "fp").distinct()


def parities(hashes: np.ndarray) -> np.ndarray:
    """64 * MARKS bits: whether an odd number of the set's shingles falls on each place."""
    odd = np.bincount((hashes >> np.uint64(40)).astype(np.int64) % (64 * MARKS), minlength=64 * MARKS) & 1
    return np.packbits(odd.astype(bool), bitorder="little").view("<i8")


def sets_of(docs: DataFrame, wanted: DataFrame, words_each: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (node, fp, hashes, marks) of the wanted (node, fp)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = list(shingle_sets(part.column(2).to_pylist(), words_each))
                held, even = [h.astype("<u8").tobytes() for h in sets], [parities(h) for h in sets]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(held, pa.binary()), pa.array(even, pa.list_(pa.int64()))], names=["node", "fp", "hashes", "marks"])

    data = docs.select(F.col(id_col).cast("long").alias("node"), F.col(text_col).alias("text"))
    few = F.broadcast(wanted) if wanted.count() <= WANTED else wanted
    return data.join(few, "node").select("node", "fp", "text").mapInArrow(trimmed(run), "node long, fp long, hashes binary, marks array<long>")


def counts(sets: DataFrame) -> np.ndarray:
    """How many sets hold a shingle, by bucket of its hash; BUCKETS numbers to the driver, whatever the input."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BUCKETS, np.int64)
        for batch in batches:
            for x in batch.column(0):
                np.add.at(total, (np.frombuffer(x.as_buffer(), "<u8") % BUCKETS).astype(np.int64), 1)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["bucket", "n"])

    got = sets.select("hashes").mapInArrow(trimmed(run), "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(BUCKETS, np.int64)
    out[got["bucket"].to_numpy()] = got["n"].to_numpy()
    return out


def prefixes(sets: DataFrame, similarity: float) -> DataFrame:
    """Rows (token, pos, n, fp, node) of every member's prefix; shingles that no other set holds are left out."""
    shared = sets.sparkSession.sparkContext.broadcast(counts(sets))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        many = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                tokens, places, sizes = [], [], []
                for x in part.column(2):
                    h = np.frombuffer(x.as_buffer(), "<u8")
                    held = many[(h % BUCKETS).astype(np.int64)]
                    first = np.lexsort((h, held))[: len(h) - math.ceil(similarity * len(h) - 1e-9) + 1]
                    pos = np.flatnonzero(held[first] > 1)
                    tokens.append(h[first[pos]].view(np.int64))
                    places.append(pos.astype(np.int32))
                    sizes.append(len(h))
                each = np.array([len(t) for t in tokens], np.int64)
                of = pa.array(np.repeat(np.arange(part.num_rows), each))
                cat = lambda xs, kind: pa.array(np.concatenate(xs) if xs else np.empty(0, kind))
                yield pa.RecordBatch.from_arrays([cat(tokens, np.int64), cat(places, np.int32), pa.array(np.repeat(np.array(sizes, np.int32), each)), part.column(1).take(of), part.column(0).take(of)], names=["token", "pos", "n", "fp", "node"])

    return sets.select("node", "fp", "hashes").mapInArrow(trimmed(run), "token long, pos int, n int, fp long, node long")


def shared_tokens(rows: DataFrame) -> DataFrame:
    """The rows whose token is in several prefixes, with how many such tokens of their node come before (column before)."""
    several = rows.groupBy("token").agg(F.count(F.lit(1)).alias("prefixes")).where("prefixes > 1").select("token")
    order = Window.partitionBy("node").orderBy("pos")  # a node's prefix: a fifth of its shingles at most
    return rows.join(several, "token").withColumn("before", (F.row_number().over(order) - 1).cast("int"))


def _fits(similarity: float, x: tuple, y: tuple) -> np.ndarray:
    """Which pairs of (before, pos, n, fp, marks...) can be similar enough: two sets share at most what both have in several
    prefixes before the token, the token, and what follows; where their parities differ, one has a shingle that the other has not."""
    (a, p, n, f, *v), (b, q, m, g, *w) = x, y
    overlap = np.minimum(a, b) + 1 + np.minimum(n - p, m - q) - 1
    near = np.bitwise_count((f ^ g).view(np.uint64)) <= FAR
    ok = near & ((1 + similarity) * overlap >= similarity * (n + m) - 1e-6)
    if v:
        at = np.flatnonzero(ok)
        some = lambda c: c[at] if c.ndim else c
        apart = sum(np.bitwise_count((some(i) ^ some(j)).view(np.uint64)).astype(np.int64) for i, j in zip(v, w))
        ok[at] = (1 + similarity) * apart <= (1 - similarity) * (some(n) + some(m)) + 1e-6
    return ok


def _pairs(x: np.ndarray, y: np.ndarray, cut: np.ndarray | None = None) -> pa.RecordBatch:
    cut = np.zeros(len(x), bool) if cut is None else cut
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(cut)], names=["a", "b", "more"])


def neighbours(rows: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) at most GAPS apart in the order of a token's members, within each partition of that order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            token, before, pos, n, fp, node = (c.to_numpy().astype(np.int64) for c in batch.columns)
            for gap in range(1, min(GAPS, len(token) - 1) + 1):
                at = np.flatnonzero(token[gap:] == token[:-gap])
                at = at[_fits(similarity, (before[at], pos[at], n[at], fp[at]), (before[at + gap], pos[at + gap], n[at + gap], fp[at + gap]))]
                if len(at):
                    yield _pairs(node[at], node[at + gap])

    order = ["token", "fp", "node"]
    dealt = rows.select("token", "before", "pos", "n", "fp", "node").repartitionByRange(shuffle_width(rows.sparkSession), *order).sortWithinPartitions(*order)
    return dealt.mapInArrow(trimmed(run), "a long, b long, more boolean").select("a", "b").distinct()


def across(rows: DataFrame, similarity: float, first: int | None, marks: DataFrame | None = None) -> DataFrame:
    """Pairs (a, b, more) of different components (column root) that share a token; of a row and another component only
    the `first` nearest where given, then with more set. marks: (node, marks) of the sets, to leave out further pairs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols in _whole_keys(batches):
            key, block = cols[0], cols[7]
            starts = np.flatnonzero(np.diff(key, prepend=key[0] - 1))
            size = np.diff(np.append(starts, len(key)))
            # small groups are compared at each distance of rows together, large ones row by row
            large = np.repeat((size > SMALL) | (np.minimum.reduceat(block, starts) != np.maximum.reduceat(block, starts)), size)
            few = [c[~large] for c in cols]
            for gap in range(1, SMALL):
                at = np.flatnonzero(few[0][gap:] == few[0][:-gap])
                if not len(at):
                    break
                to = at + gap
                other = few[6][at] != few[6][to]
                at, to = at[other], to[other]
                bound = few[1:5] + few[8:]
                ok = _fits(similarity, tuple(c[at] for c in bound), tuple(c[to] for c in bound))
                if ok.any():
                    yield _pairs(few[5][at[ok]], few[5][to[ok]])
            for x, y in zip(starts.tolist(), (starts + size).tolist()):
                if large[x]:
                    yield from pairs_of(*(c[x:y] for c in cols[1:]))

    def pairs_of(before: np.ndarray, pos: np.ndarray, n: np.ndarray, fp: np.ndarray, node: np.ndarray, root: np.ndarray, block: np.ndarray, *marks: np.ndarray) -> Iterator[pa.RecordBatch]:
        if (root == root[0]).all():
            return
        two = (block != block[0]).any()  # of two blocks only rows across are compared; each alone has its own turn
        for i in range(len(node) - 1):
            rest = slice(i + 1, None)
            other = root[rest] != root[i]
            if two:
                other &= block[rest] != block[i]
            at = np.flatnonzero(other) + i + 1
            bound = (before, pos, n, fp, *marks)
            at = at[_fits(similarity, tuple(c[at] for c in bound), tuple(c[i] for c in bound))]
            if not len(at):
                continue
            more = np.zeros(len(at), bool)
            if first and len(at) > first:
                far = np.bitwise_count((fp[at] ^ fp[i]).view(np.uint64))
                at = at[np.lexsort((far, root[at]))]
                nth = np.arange(len(at)) - np.searchsorted(root[at], root[at])
                keep = nth < first
                more = nth[keep] == first - 1
                at = at[keep]
            yield _pairs(np.full(len(at), node[i]), node[at], more)

    sizes = rows.groupBy("token").agg(F.count(F.lit(1)).alias("size"), F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 <> r1")
    open_ = rows.join(sizes.select("token", F.ceil(F.col("size") / BLOCK).cast("int").alias("blocks")), "token")
    own = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    open_ = open_.withColumn("block", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    key = F.xxhash64("token", F.least("block", "other"), F.greatest("block", "other"))
    open_ = open_.select(key.alias("key"), "before", "pos", "n", "fp", "node", "root", "block")
    if marks is not None:
        open_ = open_.join(marks, "node").select("key", "before", "pos", "n", "fp", "node", "root", "block", *[F.col("marks")[i].alias(f"mark{i}") for i in range(MARKS)])
    dealt = open_.repartition(shuffle_width(rows.sparkSession), "key").sortWithinPartitions("key")
    return dealt.mapInArrow(trimmed(run), "a long, b long, more boolean").groupBy("a", "b").agg(F.max("more").alias("more"))


def _whole_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """The columns in pieces that hold all rows of their keys; rows come sorted by the first column."""
    parts: list[list[np.ndarray]] = []  # of the key that may go on in the next batch
    for batch in batches:
        cols = [c.to_numpy().astype(np.int64) for c in batch.columns]
        if not len(cols[0]):
            continue
        if parts and cols[0][0] == cols[0][-1] == parts[0][0][0]:
            parts.append(cols)
            continue
        held = [np.concatenate(x) for x in zip(*parts, cols)]
        last = int(np.searchsorted(held[0], held[0][-1]))
        if last:
            yield [c[:last] for c in held]
        parts = [[c[last:] for c in held]]
    if parts:
        yield [np.concatenate(x) for x in zip(*parts)]


def verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose sets are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = []
            for x, y in zip(batch.column(2), batch.column(3)):
                p, q = (np.frombuffer(v.as_buffer(), "<u8") for v in (x, y))
                both = len(np.intersect1d(p, q, assume_unique=True))
                ok.append(both >= similarity * (len(p) + len(q) - both) - 1e-9)
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    full = pairs.join(sets.select(F.col("node").alias("a"), F.col("hashes").alias("x")), "a").join(sets.select(F.col("node").alias("b"), F.col("hashes").alias("y")), "b")
    return full.select("a", "b", "x", "y").mapInArrow(trimmed(run), "a long, b long")


def near_duplicates(docs: DataFrame, words_each: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, component) of unique ids: component is the least id reachable over links, the row's own included."""
    every = stored(prints(docs, words_each, id_col, text_col), "prints")
    nodes = every.groupBy("digest").agg(F.min("id").alias("node"), F.first("fp").alias("fp"), F.first("keys").alias("keys"))
    nodes = stored(nodes, "nodes")
    same = alike(nodes)
    ends = nodes.join(same.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "node").select("node", "fp")
    sets = stored(sets_of(docs, stored(members(nodes).unionByName(ends).distinct(), "members"), words_each, id_col, text_col), "sets")
    every_row = stored(prefixes(sets, similarity), "prefixes")
    rows = stored(shared_tokens(every_row), "prefixes")
    discard(every_row)
    links = stored(verified(same.unionByName(neighbours(rows, similarity)).distinct(), sets, similarity), "links")
    labels = None if links.isEmpty() else components(links)
    tested = None
    for first in (FIRST, None):
        rooted = rows.withColumn("root", F.col("node")) if labels is None else rows.join(labels, "node", "left").withColumn("root", F.coalesce("root", "node"))
        wanted = across(rooted, similarity, first, sets.select("node", "marks"))
        if tested is not None:
            wanted = wanted.join(tested.select("a", "b"), ["a", "b"], "left_anti")  # what was not similar enough is not looked at again
        pairs = tested = stored(wanted, "pairs")
        found = stored(verified(pairs.select("a", "b"), sets, similarity), "links")
        if not found.isEmpty():
            links = links.unionByName(found)
            labels = components(links)
        if pairs.where("more").isEmpty():
            break
    out = every.select("id", "digest").join(nodes.select("digest", "node"), "digest")
    if labels is None:
        out = out.select("id", F.col("node").alias("component"))
    else:
        out = out.join(labels, "node", "left").select("id", F.coalesce("root", "node").alias("component"))
    out = stored(out, "groups")
    discard(every, nodes, same, sets, rows, pairs)
    return out
