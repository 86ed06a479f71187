"""SimHash near-duplicates through one-wildcard segment variants.

A fingerprint is cut into fewer segments than would force an exact match: with ``bits`` allowed differences and
``bits // 2 + 1`` segments, some segment of two linked fingerprints differs in one bit at most. Each segment is indexed
once per position with that bit wildcarded; rows meeting under a variant are verified by counting bits. In a variant's
group not all pairs are given out: links are searched breadth first and a spanning forest is returned, which keeps
every component whole. Texts with one fingerprint are one node, so copies cost nothing.

Cases: null or wordless text - fingerprint zero, linked like any other; fewer words than a shingle - the whole sequence
is the only shingle; repeated rows and ids - same fingerprint, same component; null id - kept, its component is the
least id of the group (null if there is none); empty table - no rows; other columns are not read; whole texts are used.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import discard, shuffle_width, stored, trimmed
from gainclust.llm.components import components

SEED, WIDTH = 42, 64
BLOCK = 8192  # fingerprints of one key searched together; more are dealt out in pairs of blocks
SLICE = 1 << 22  # bytes of text whose shingles are hashed together


def shingle_hashes(text: str | None, words_each: int) -> np.ndarray:
    """XXH64 of every shingle; empty if there is no word."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: only A-Z change, only ASCII white space splits
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = max(len(words) - words_each + 1, 1)
    last = ends[min(words_each, len(words)) - 1 :][:n].tolist()
    h = xxhash.xxh64_intdigest
    return np.fromiter((h(joined[s:e], SEED) for s, e in zip(starts[:n].tolist(), last)), np.uint64, n)


def fingerprints_of(texts: list, words_each: int = 3) -> np.ndarray:
    """One unsigned 64-bit fingerprint per text: a bit is set if over half of the shingle hashes have it."""
    out = np.zeros(len(texts), np.uint64)
    held: list[np.ndarray] = []
    rows: list[int] = []
    size = 0

    def flush() -> None:
        nonlocal size
        if held:
            n = np.array([len(x) for x in held])
            bits = np.unpackbits(np.concatenate(held).astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            starts = np.concatenate([[0], np.cumsum(n)[:-1]])
            ones = np.add.reduceat(bits, starts, axis=0, dtype=np.int64)
            out[rows] = np.packbits(2 * ones > n[:, None], axis=1, bitorder="little").view("<u8").ravel()
        held.clear(), rows.clear()
        size = 0

    for i, text in enumerate(texts):
        h = shingle_hashes(text, words_each)
        if len(h):
            held.append(h)
            rows.append(i)
            size += len(h)
        if size > SLICE // 32:
            flush()
    flush()
    return out


def fingerprints(docs: DataFrame, words_each: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, fp); fp is the fingerprint's bits in a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                fp = fingerprints_of(part.column(1).to_pylist(), words_each)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fp.view(np.int64))], names=["id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(trimmed(run), "id long, fp long")


def spanning_links(fps: np.ndarray, bits: int) -> list[tuple[int, int]]:
    """Links of a forest with the components of {pairs within bits}: each search front takes what it reaches out of the rest."""
    rest, out = fps, []
    while len(rest):
        front, rest = [rest[0]], rest[1:]
        while front and len(rest):
            one = front.pop()
            near = np.bitwise_count((rest ^ one).view(np.uint64)) <= bits  # of signed numbers it would count the absolute value's
            if near.any():
                got = rest[near]
                out += [(int(one), int(x)) for x in got]
                front += list(got)
                rest = rest[~near]
    return out


def variant_links(fps: DataFrame, bits: int = 3) -> DataFrame:
    """Links (a, b) between distinct fingerprints (column fp, each once) that keep the components whole."""
    segments = bits // 2 + 1
    width = -(-WIDTH // segments)
    spark = fps.sparkSession

    keys = []
    for s in range(segments):
        low, size = s * width, min(width, WIDTH - s * width)
        mask = (1 << size) - 1
        segment = F.shiftrightunsigned("fp", low).bitwiseAND(F.lit(mask))
        for j in range(size):
            # segment and position number in the upper bits, the segment without that bit below
            tag = (s * width + j) << width
            keys.append(segment.bitwiseAND(F.lit(mask & ~(1 << j))).bitwiseOR(F.lit(tag)))
    if width + 6 > 63:
        raise ValueError("needs at least two segments: bits >= 2")
    variants = fps.select("fp", F.explode(F.array(*keys)).alias("key"))

    def verified(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_k, kept_f = np.empty(0, np.int64), np.empty(0, np.int64)
        large = None  # the key whose rows are handed on
        for batch in batches:
            k = np.concatenate([kept_k, batch.column(0).to_numpy()])
            f = np.concatenate([kept_f, batch.column(1).to_numpy()])
            if not len(k):
                continue
            if large is not None:
                end = int(np.searchsorted(k, large, "right"))
                yield _links([], f[:end], large)
                k, f = k[end:], f[end:]
                large = None if len(k) else large
            last = int(np.searchsorted(k, k[-1])) if len(k) else 0  # the last key may go on in the next batch
            yield from _grouped(k[:last], f[:last], bits)
            kept_k, kept_f = k[last:], f[last:]
            if len(kept_k) > BLOCK:
                large = int(kept_k[0])
                yield _links([], kept_f, large)
                kept_k, kept_f = kept_k[:0], kept_f[:0]
        yield from _grouped(kept_k, kept_f, bits)

    sorted_keys = variants.select("key", "fp").repartition(shuffle_width(spark), "key").sortWithinPartitions("key")
    found = stored(sorted_keys.mapInArrow(trimmed(verified), "a long, b long, key long"), "variant-links")
    links, open_ = found.where("key IS NULL").select("a", "b"), found.where("key IS NOT NULL").select("key", F.col("a").alias("fp"))
    return links if open_.isEmpty() else links.unionByName(_block_links(open_, bits))


def _links(pairs: list[tuple[int, int]], handed_on: np.ndarray, key: int | None) -> pa.RecordBatch:
    """Links (a, b), or rows of a key that is too large (a the fingerprint)."""
    a, b = zip(*pairs) if pairs else ((), ())
    n = len(handed_on)
    a = np.concatenate([np.array(a, np.int64), handed_on])
    return pa.RecordBatch.from_arrays([pa.array(a), pa.array([*b, *[None] * n], pa.int64()), pa.array([*[None] * len(b), *[key] * n], pa.int64())], names=["a", "b", "key"])


def _grouped(k: np.ndarray, f: np.ndarray, bits: int) -> Iterator[pa.RecordBatch]:
    edge = np.flatnonzero(np.diff(k)) + 1
    starts, ends = np.concatenate([[0], edge]), np.concatenate([edge, [len(k)]])
    pairs: list[tuple[int, int]] = []
    for s, e in zip(*(x[ends - starts > 1].tolist() for x in (starts, ends))):
        if e - s > BLOCK:
            yield _links([], f[s:e], int(k[s]))
        else:
            pairs += spanning_links(f[s:e], bits)
    yield _links(pairs, np.empty(0, np.int64), None)


def _block_links(rows: DataFrame, bits: int) -> DataFrame:
    """Links within keys of over BLOCK fingerprints: every two blocks of a key meet in one task of bounded size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_k, held_f = np.empty(0, np.int64), np.empty(0, np.int64)
        for batch in [*batches, None]:
            if batch is not None:
                held_k, held_f = np.concatenate([held_k, batch.column(0).to_numpy()]), np.concatenate([held_f, batch.column(1).to_numpy()])
            last = int(np.searchsorted(held_k, held_k[-1])) if batch is not None and len(held_k) else len(held_k)
            edge = np.flatnonzero(np.diff(held_k[:last])) + 1
            pairs = [p for part in np.split(held_f[:last], edge) for p in spanning_links(part, bits)]
            a, b = zip(*pairs) if pairs else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])
            held_k, held_f = held_k[last:], held_f[last:]

    sizes = rows.groupBy("key").agg(F.ceil(F.count(F.lit(1)) * 2 / BLOCK).cast("int").alias("blocks"))
    own = F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int")
    dealt = rows.join(sizes, "key").withColumn("block", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    both = F.xxhash64("key", F.least("block", "other"), F.greatest("block", "other"))
    lined = dealt.select(both.alias("pair"), "fp").repartition(shuffle_width(rows.sparkSession), "pair").sortWithinPartitions("pair")
    return lined.mapInArrow(trimmed(run), "a long, b long")


def near_duplicates(docs: DataFrame, words_each: int = 3, bits: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, fp, component): component is the least id reachable over links, the row's own included."""
    prints = stored(fingerprints(docs, words_each, id_col, text_col), "prints")
    nodes = stored(prints.groupBy("fp").agg(F.min("id").alias("least")), "nodes")
    links = stored(variant_links(nodes.select("fp"), bits), "links")
    roots = components(links)
    # the least id of every fingerprint in a component
    linked = roots.join(nodes, roots["node"] == nodes["fp"]).select("fp", "root", "least")
    least = linked.groupBy("root").agg(F.min("least").alias("component"))
    linked = stored(linked.join(least, "root").select("fp", "component"), "linked")
    discard(links, roots)
    alone = nodes.join(linked, "fp", "left_anti").select("fp", F.col("least").alias("component"))
    every = linked.unionByName(alone)
    return prints.join(every, "fp").select("id", "fp", "component")
