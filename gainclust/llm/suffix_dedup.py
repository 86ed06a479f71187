"""Removal of long byte strings that occur more than once, by hash-compared suffix sorting.

A byte goes if some ``window``-byte string over it also starts anywhere else in the input. Two equal windows have
the same minimizer (the gram of least hash) at the same offset, so only windows around equal grams can be equal:

1. Each text is cut into runs of windows that share a minimizer; a run is known by its gram's hash, by a hash of its
   bytes and by its place. Runs of equal bytes are one *context*, whose windows all repeat if it occurs twice.
2. The contexts of a gram are sorted by their suffix from the gram on: mergesort whose comparisons find the common
   extension by binary search over prefix polynomial hashes. Common extensions to the left complete the matches.
   Every extension that decides is compared byte by byte, so a hash collision cannot remove text.
3. A gram with over ``HOT`` contexts is no group for one task: its windows are counted by two hashes with an aggregate
   that combines before the shuffle.

Cases: null text - as empty; texts shorter than the window - kept whole; repeated rows and ids - each row is an
occurrence of its own and keeps its row; null id - kept; empty table - no rows; other columns are not read; texts of
any length are taken whole, long ones in overlapping pieces. Strings are judged on the input, not on what is left.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import discard, shuffle_width, stored, trimmed
from gainclust.llm.windows import PrefixHash, minimizer_runs, mixed

GRAM, HOT = 32, 64
STEP_BYTES = 1 << 19  # text hashed at once; longer texts are cut with overlap
KERNEL_BYTES = 1 << 20  # contexts sorted at once
_SHIFT = 12  # a run's place: first window, windows and offset of its gram in one long


def _pieces(texts: list[bytes | None], window: int) -> Iterator[list[tuple[int, int, bytes]]]:
    """(row, place in its text, bytes) in lots of about STEP_BYTES; pieces overlap by window - 1 bytes."""
    lot, size = [], 0
    for row, text in enumerate(texts):
        if text is None or len(text) < window:
            continue
        for a in range(0, len(text) - window + 1, STEP_BYTES):
            piece = text[a : a + STEP_BYTES + window - 1] if a or len(text) > STEP_BYTES + window - 1 else text
            lot.append((row, a, piece))
            size += len(piece)
            if size >= STEP_BYTES:
                yield lot
                lot, size = [], 0
    if lot:
        yield lot


def runs_of(texts: list[bytes | None], window: int) -> tuple[np.ndarray, ...]:
    """Per run: row, gram hash, context hash, packed place (first window, count, gram offset)."""
    out: list[tuple] = []
    for lot in _pieces(texts, window):
        data = np.frombuffer(b"".join(p for _, _, p in lot), np.uint8)
        sizes = np.array([len(p) for _, _, p in lot])
        starts = np.cumsum(sizes) - sizes
        prefix = PrefixHash(data)
        grams = prefix.grams(GRAM)
        first, n, place = minimizer_runs(grams, starts, sizes, window, GRAM)
        piece = np.searchsorted(starts, first, "right") - 1
        local = first - starts[piece] + np.array([a for _, a, _ in lot])[piece]
        offset = place - first
        whole = prefix.of(first, first + n + window - 1)
        context = mixed(whole + mixed((n << _SHIFT | offset).astype(np.uint64)))
        packed = (local << 2 * _SHIFT) | (n << _SHIFT) | offset
        out.append((np.array([r for r, _, _ in lot])[piece], grams[place].view(np.int64), context.view(np.int64), packed))
    if not out:
        return (np.empty(0, np.int64),) * 4
    return tuple(np.concatenate(x) for x in zip(*out))


def common(prefix: PrefixHash, a: np.ndarray, b: np.ndarray, limit: np.ndarray, back: bool = False) -> np.ndarray:
    """Length up to limit of the common extension of places a and b, by binary search on hashes."""
    found = np.zeros(len(a), np.int64)
    step = 1 << max(int(limit.max(initial=0)).bit_length() - 1, 0)
    while step:
        fits = found + step <= limit
        at = np.flatnonzero(fits)
        x, y = (a[at] - found[at] - step, b[at] - found[at] - step) if back else (a[at] + found[at], b[at] + found[at])
        same = prefix.of(x, x + step) == prefix.of(y, y + step)
        found[at[same]] += step
        step >>= 1
    return found


def checked(data: np.ndarray, a: np.ndarray, b: np.ndarray, n: np.ndarray, back: bool = False) -> np.ndarray:
    """n, or less where the bytes disagree with their hashes."""
    out = n.copy()
    for at in range(0, len(a), 4096):
        s = slice(at, at + 4096)
        width = int(n[s].max(initial=0))
        k = np.arange(width)
        k = -1 - k if back else k
        top = len(data) - 1
        differ = data[np.clip(a[s][:, None] + k, 0, top)] != data[np.clip(b[s][:, None] + k, 0, top)]
        differ &= np.arange(width) < n[s][:, None]
        bad = differ.any(1)
        if bad.any():
            out[s][bad] = np.argmax(differ[bad], 1)
    return out


def suffix_order(prefix: PrefixHash, data: np.ndarray, start: np.ndarray, size: np.ndarray, group: np.ndarray) -> np.ndarray:
    """Order of suffixes (start, size) by group (given ascending), then bytes: mergesort of all groups at once."""
    m = len(start)
    order = np.arange(m)
    first = np.searchsorted(group, group)
    nth, many = order - first, np.searchsorted(group, group, "right") - first

    def less(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        limit = np.minimum(size[i], size[j])
        n = common(prefix, start[i], start[j], limit)
        ended = n == limit
        top = len(data) - 1
        return np.where(ended, size[i] < size[j], data[np.minimum(start[i] + n, top)] < data[np.minimum(start[j] + n, top)])

    width = 1
    while width < many.max(initial=0):
        base = first + nth // (2 * width) * (2 * width)
        split, end = base + width, np.minimum(base + 2 * width, first + many)
        right = nth % (2 * width) >= width
        works = split < end
        lo, hi = np.where(right, base, split), np.where(right, split, end)
        hi = np.where(works, hi, lo)
        begun = lo.copy()
        while len(at := np.flatnonzero(lo < hi)):
            mid = (lo[at] + hi[at]) // 2
            own, other = order[at], order[mid]
            # left runs count strictly smaller partners, right runs smaller or equal ones: a stable merge
            up = np.where(right[at], ~less(own, other), less(other, own))
            lo[at] = np.where(up, mid + 1, lo[at])
            hi[at] = np.where(up, hi[at], mid)
        target = np.where(works, np.where(right, np.arange(m) - width, np.arange(m)) + (lo - begun), np.arange(m))
        merged = np.empty(m, np.int64)
        merged[target] = order
        order = merged
        width *= 2
    return order


def repeated_windows(groups: np.ndarray, contexts: list[bytes], n: np.ndarray, offset: np.ndarray, count: np.ndarray, window: int) -> list[np.ndarray]:
    """Per context that occurs once the numbers of its windows that other contexts have too; groups ascending, contexts of a group distinct."""
    m = len(contexts)
    sizes = np.fromiter(map(len, contexts), np.int64, m)
    begin = np.cumsum(sizes) - sizes
    data = np.frombuffer(b"".join(contexts), np.uint8)
    prefix = PrefixHash(data)
    start, right = begin + offset, sizes - offset
    order = suffix_order(prefix, data, start, right, groups)
    g, s, r, o = groups[order], start[order], right[order], offset[order]
    hit = np.zeros((m, window + 1), np.int32)  # difference array over the gram's offset in the window
    # lcp of neighbours in the suffix order; of others the running minimum
    near = common(prefix, s[:-1], s[1:], np.minimum(np.minimum(r[:-1], r[1:]), window))
    near = checked(data, s[:-1], s[1:], np.where(g[:-1] == g[1:], near, 0))
    run, t = near.copy(), 1
    while t < m:
        a = np.flatnonzero(g[:-t] == g[t:])
        if not len(a):
            break
        b = a + t
        lcp = run[a]
        lcs = common(prefix, s[a], s[b], np.minimum(o[a], o[b]), back=True)
        some = lcp + lcs >= window
        if some.any():
            a, b, lcp, lcs = a[some], b[some], lcp[some], lcs[some]
            lcs = checked(data, s[a], s[b], lcs, back=True)
            for x in (a, b):
                ok = lcp + lcs >= window
                np.add.at(hit, (order[x[ok]], np.maximum(window - lcp[ok], 0)), 1)
                np.add.at(hit, (order[x[ok]], lcs[ok] + 1), -1)
        run = np.minimum(run[:-1], near[t:])
        t += 1
    covered = np.cumsum(hit, axis=1) > 0
    out = []
    for i in range(m):
        # contexts that occur more often are known to repeat as a whole
        out.append(np.flatnonzero(covered[i, offset[i] - np.arange(n[i])]) if count[i] == 1 else np.empty(0, np.int64))
    return out


def spans(numbers: np.ndarray) -> list[int]:
    """Ascending numbers as first, length, first, length, ..."""
    if not len(numbers):
        return []
    edge = np.flatnonzero(np.diff(numbers) != 1)
    first = numbers[np.concatenate([[0], edge + 1])]
    last = numbers[np.concatenate([edge, [len(numbers) - 1]])]
    return np.stack([first, last - first + 1], 1).ravel().tolist()


def _contexts(docs: DataFrame, wanted: DataFrame, window: int) -> DataFrame:
    """Each wanted context cut from one text: its bytes or, for a hot gram, two hashes of every window. One shuffle of the texts."""
    per_doc = wanted.groupBy("k", "k2").agg(F.collect_list(F.struct("gram", "context", "place", "times", "hot")).alias("wanted"))
    schema = "gram long, context long, place long, times long, bytes binary, windows array<struct<j:int,w1:long,w2:long>>"
    window_schema = pa.list_(pa.struct([("j", pa.int32()), ("w1", pa.int64()), ("w2", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                rows: list[tuple] = []
                for text, items in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    for w in items:
                        first, n = w["place"] >> 2 * _SHIFT, w["place"] >> _SHIFT & (1 << _SHIFT) - 1
                        cut, windows = text[first : first + n + window - 1], None
                        if w["hot"]:
                            data = np.frombuffer(cut, np.uint8)
                            j = np.arange(n)
                            w1, w2 = (mixed(PrefixHash(x).of(j, j + window)).view(np.int64) for x in (data, data[::-1] ^ np.uint8(0x5A)))
                            cut, windows = None, [{"j": int(a), "w1": int(b), "w2": int(c)} for a, b, c in zip(j, w1, w2[::-1])]
                        rows.append((w["gram"], w["context"], w["place"], w["times"], cut, windows))
                cols = list(zip(*rows)) or [()] * 6
                arrays = [pa.array(c, pa.int64()) for c in cols[:4]] + [pa.array(cols[4], pa.binary()), pa.array(cols[5], window_schema)]
                yield pa.RecordBatch.from_arrays(arrays, names=["gram", "context", "place", "times", "bytes", "windows"])

    # one text per key suffices: equal keys mean equal texts
    return docs.select("k", "k2", "bytes").join(per_doc, ["k", "k2"]).select("bytes", "wanted").mapInArrow(trimmed(run), schema)


def _sorted_groups(contexts: DataFrame, window: int) -> DataFrame:
    """Rows (gram, context, spans) from the suffix sort of each gram's contexts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def done(rows: list[tuple]) -> pa.RecordBatch:
            # rows of one text may have been cut once for each of its copies
            rows = list({r[:3] + (r[4],): r for r in rows}.values())
            rows.sort(key=lambda r: r[0])
            place = np.array([r[2] for r in rows], np.int64)
            n, offset = place >> _SHIFT & (1 << _SHIFT) - 1, place & (1 << _SHIFT) - 1
            found = repeated_windows(np.array([r[0] for r in rows]), [r[4] for r in rows], n, offset, np.array([r[3] for r in rows]), window) if rows else []
            out = [(r[0], r[1], spans(x)) for r, x in zip(rows, found) if len(x)]
            g, c, s = zip(*out) if out else ((), (), ())
            return pa.RecordBatch.from_arrays([pa.array(g, pa.int64()), pa.array(c, pa.int64()), pa.array(s, pa.list_(pa.int32()))], names=["gram", "context", "spans"])

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if held and size >= KERNEL_BYTES and row[0] != held[-1][0]:
                    yield done(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[4])
        yield done(held)

    spark = contexts.sparkSession
    lined = contexts.repartition(shuffle_width(spark), "gram").sortWithinPartitions("gram")
    return lined.mapInArrow(trimmed(run), "gram long, context long, spans array<int>")


def _repeated_hashes(windows: DataFrame) -> DataFrame:
    """Of windows (gram, context, times, j, w1, w2) the places (gram, context, j), of contexts that occur once, whose two
    hashes occur at another place or in a context that occurs more often. One pass over the sorted hashes, which
    remembers one place, however many share a hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple | None = None  # the key that may go on, whether it is known to repeat, and its last place
        for batch in batches:
            if not batch.num_rows:
                continue
            w1, w2, gram, context, j, times = (c.to_numpy().astype(np.int64) for c in batch.columns)
            place = np.stack([gram, context, j], 1)
            new = np.concatenate([[True], (w1[1:] != w1[:-1]) | (w2[1:] != w2[:-1])])
            starts = np.flatnonzero(new)
            ends = np.append(starts[1:], len(w1)) - 1
            again = (np.maximum.reduceat(times, starts) > 1) | (place[starts] != place[ends]).any(1)
            same = np.concatenate([[False], ~new[1:] & (place[1:] == place[:-1]).all(1)])  # a repeated row gives its windows again
            out = []
            if last is not None and last[0] == (w1[0], w2[0]):
                _, known, before = last
                same[0] = before == tuple(place[0].tolist())
                again[0] |= known or not same[0]
                if again[0] and not known:
                    out.append(np.array([before], np.int64))
            of = np.cumsum(new) - 1
            out.append(place[again[of] & (times == 1) & ~same])
            last = ((w1[-1], w2[-1]), bool(again[-1]), tuple(place[-1].tolist()))
            rows = np.concatenate(out)
            yield pa.RecordBatch.from_arrays([pa.array(rows[:, 0]), pa.array(rows[:, 1]), pa.array(rows[:, 2].astype(np.int32))], names=["gram", "context", "j"])

    order = ["w1", "w2", "gram", "context", "j"]
    lined = windows.select(*order, "times").repartition(shuffle_width(windows.sparkSession), "w1", "w2").sortWithinPartitions(*order)
    return lined.mapInArrow(trimmed(run), "gram long, context long, j int")


def repeated_spans(docs: DataFrame, window: int) -> DataFrame:
    """From rows (k, k2, bytes): per key the byte spans to remove, as (k, k2, gone array<struct<a,b>>), not merged."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                row, gram, context, place = runs_of(part.column(2).to_pylist(), window)
                of = pa.array(row)
                yield pa.RecordBatch.from_arrays([part.column(0).take(of), part.column(1).take(of), pa.array(gram), pa.array(context), pa.array(place)], names=["k", "k2", "gram", "context", "place"])

    long_enough = docs.where(F.octet_length("bytes") >= window).select("k", "k2", "bytes")
    runs = stored(long_enough.mapInArrow(trimmed(scan), "k long, k2 int, gram long, context long, place long"), "runs")
    own = runs.groupBy("gram", "context").agg(F.count(F.lit(1)).alias("times"), F.min(F.struct("k", "k2", "place")).alias("at"))
    own = stored(own.select("gram", "context", "times", "at.k", "at.k2", "at.place"), "contexts")
    grams = own.groupBy("gram").agg(F.count(F.lit(1)).alias("contexts"), F.sum("times").alias("occurrences"), F.min("times").alias("least")).where("occurrences > 1")
    grams = grams.select("gram", "least", (F.col("contexts") > HOT).alias("hot"))
    wanted = stored(own.join(grams, "gram").select("k", "k2", "gram", "context", "place", "times", "hot", "least"), "wanted")
    discard(own)
    # a context that occurs twice repeats in all its windows; only grams with others are looked into
    n = F.shiftright("place", _SHIFT).bitwiseAND(F.lit((1 << _SHIFT) - 1)).cast("int")
    whole = wanted.where("times > 1").select("gram", "context", F.array(F.lit(0), n).alias("spans"))

    cut = stored(_contexts(docs, wanted.where("least = 1"), window), "cut")
    cold = _sorted_groups(cut.where("windows IS NULL").drop("windows"), window)
    every = cut.where("windows IS NOT NULL").select("gram", "context", "times", F.explode("windows").alias("w")).select("gram", "context", "times", "w.*")
    warm = _repeated_hashes(every).groupBy("gram", "context").agg(F.flatten(F.collect_list(F.array(F.col("j"), F.lit(1)))).alias("spans"))
    flags = stored(whole.unionByName(cold).unionByName(warm), "flags")
    discard(wanted, cut)

    hits = runs.join(flags, ["gram", "context"]).select("k", "k2", F.shiftright("place", 2 * _SHIFT).alias("first"), "spans")
    pair = lambda i: F.struct((F.col("first") + F.element_at("spans", 2 * i + 1)).alias("a"), (F.col("first") + F.element_at("spans", 2 * i + 1) + F.element_at("spans", 2 * i + 2) + window - 1).alias("b"))
    lists = hits.select("k", "k2", F.transform(F.sequence(F.lit(0), (F.size("spans") / 2 - 1).cast("int")), pair).alias("own"))
    gone = stored(lists.groupBy("k", "k2").agg(F.flatten(F.collect_list("own")).alias("gone")), "gone")
    discard(runs, flags)
    return gone


def merge_spans(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of half-open spans as maximal runs."""
    order = np.argsort(a, kind="stable")
    a, b = a[order], np.maximum.accumulate(b[order])
    new = np.flatnonzero(np.concatenate([[True], a[1:] > b[:-1]]))
    return a[new], b[np.append(new[1:] - 1, len(b) - 1)]


def keyed(docs: DataFrame, id_col: str, text_col: str, keep: list[Column]) -> DataFrame:
    """(k, k2, id, bytes, ...): 96 bits of two hashes tell texts with their ids apart."""
    base = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), *keep)
    second = F.shiftright(F.xxhash64(F.lit("second"), "text", "id"), 32).cast("int")
    return base.select(F.xxhash64("id", "text").alias("k"), second.alias("k2"), "id", F.col("text").cast("binary").alias("bytes"), *base.columns[2:])


#: What remove_repeats can return beside its counts, by name; text is kept without the rests of cut characters.
COLUMNS = {"kept": "binary", "kept_sha256": "string", "text": "string"}
_KINDS = {"binary": pa.binary(), "string": pa.string(), "long": pa.int64()}


def without(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    edges = [0, *(e for span in spans for e in span), len(text)]
    return b"".join(text[x:y] for x, y in zip(edges[::2], edges[1::2]))


def maximal(text: bytes, own: pa.ListScalar, min_words: int = 0) -> list[tuple[int, int]]:
    """The maximal runs of a list of spans; of those with fewer words none."""
    if not own.is_valid or not len(own.values):
        return []
    a, b = merge_spans(own.values.field(0).to_numpy(), own.values.field(1).to_numpy())
    return [(x, y) for x, y in zip(a.tolist(), b.tolist()) if not min_words or len(text[x:y].split()) >= min_words]


def remove_repeats(docs: DataFrame, window: int = 400, id_col: str = "doc_id", text_col: str = "text", keep: list[Column] | None = None, returns: tuple[str, ...] = ("kept",), min_words: int = 0) -> DataFrame:
    """One row per document: (id, n_bytes, n_removed, n_spans), the columns named in returns (see COLUMNS) and keep.

    min_words: maximal removed runs of fewer words stay. keep: further columns to carry, named apart from those above.
    """
    base = keyed(docs, id_col, text_col, keep or [])
    gone = repeated_spans(base.select("k", "k2", "bytes"), window)
    made = {"kept": lambda x: x, "kept_sha256": lambda x: hashlib.sha256(x).hexdigest(), "text": lambda x: x.decode("utf-8", "ignore")}

    def row(text: bytes, own: pa.ListScalar) -> tuple:
        spans = maximal(text, own, min_words)
        rest = without(text, spans)
        return len(text), len(text) - len(rest), len(spans), *(made[c](rest) for c in returns)

    columns = {"n_bytes": "long", "n_removed": "long", "n_spans": "long"} | {c: COLUMNS[c] for c in returns}
    return _rows(base.join(gone, ["k", "k2"], "left"), ["gone"], row, columns, base.schema.fields[4:])


def _rows(base: DataFrame, spans: list[str], row, columns: dict[str, str], carried: list) -> DataFrame:
    """id, what row(text, spans...) gives as columns, and the carried ones."""
    schema = "id long" + "".join(f", {c} {kind}" for c, kind in columns.items()) + "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in carried)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                made = [row(text, *own) for text, *own in zip(part.column(1).to_pylist(), *part.columns[2 : 2 + len(spans)])]
                cols = [pa.array([r[i] for r in made], _KINDS[kind]) for i, kind in enumerate(columns.values())]
                yield pa.RecordBatch.from_arrays([part.column(0), *cols, *part.columns[2 + len(spans) :]], names=["id", *columns, *(f.name for f in carried)])

    return base.select("id", "bytes", *spans, *(f.name for f in carried)).mapInArrow(trimmed(cut), schema)


def remove_repeats_and_passages(docs: DataFrame, window: int = 400, passage: int = 200, min_words: int = 51, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: (id, n_bytes, n_removed, n_spans, kept_sha256) as remove_repeats() has them, then
    (n_passage_bytes, n_passages, text): what repeats as strings of `passage` bytes, in maximal runs of min_words words
    or more, and the text without the two kinds of repeats.

    Strings of the longer window can repeat only inside what repeats as shorter strings, so their search runs over those
    parts alone.
    """
    if passage > window:
        raise ValueError("passage is the shorter window")
    base = keyed(docs, id_col, text_col, [])
    short = repeated_spans(base.select("k", "k2", "bytes"), passage)

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                rows = [(i, x, text[x:y]) for i, (text, own) in enumerate(zip(part.column(2).to_pylist(), part.column(3))) for x, y in maximal(text, own) if y - x >= window]
                of, place, cut = zip(*rows) if rows else ((), (), ())
                of = pa.array(of, pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0).take(of), part.column(1).take(of), pa.array(place, pa.int64()), pa.array(cut, pa.binary())], names=["k", "k2", "place", "bytes"])

    # a row of the table is a row of pieces: copies stay as many as they are
    cut = base.join(short, ["k", "k2"]).select("k", "k2", "bytes", "gone").mapInArrow(trimmed(pieces), "k long, k2 int, place long, bytes binary")
    own = [F.xxhash64("k", "k2", "place").alias("k"), F.shiftright(F.xxhash64(F.lit("second"), "place", "k2", "k"), 32).cast("int").alias("k2")]
    cut = stored(cut.select(*own, F.col("k").alias("text_k"), F.col("k2").alias("text_k2"), "place", "bytes"), "pieces")
    found = repeated_spans(cut.select("k", "k2", "bytes"), window)
    of_text = cut.select("k", "k2", "text_k", "text_k2", "place").distinct().join(found, ["k", "k2"])
    moved = F.transform("gone", lambda g: F.struct((g["a"] + F.col("place")).alias("a"), (g["b"] + F.col("place")).alias("b")))
    long_ = of_text.groupBy(F.col("text_k").alias("k"), F.col("text_k2").alias("k2")).agg(F.flatten(F.collect_list(moved)).alias("far"))
    long_ = stored(long_, "gone")
    discard(cut, found)

    def row(text: bytes, far: pa.ListScalar, near: pa.ListScalar) -> tuple:
        spans, passages = maximal(text, far), maximal(text, near, min_words)
        rest = without(text, spans)
        both = spans + passages
        if both:
            a, b = merge_spans(*(np.array(x) for x in zip(*both)))
            both = list(zip(a.tolist(), b.tolist()))
        clean = without(text, both).decode("utf-8", "ignore")
        return len(text), len(text) - len(rest), len(spans), hashlib.sha256(rest).hexdigest(), sum(y - x for x, y in passages), len(passages), clean

    columns = {"n_bytes": "long", "n_removed": "long", "n_spans": "long", "kept_sha256": "string", "n_passage_bytes": "long", "n_passages": "long", "text": "string"}
    return _rows(base.join(long_, ["k", "k2"], "left").join(short, ["k", "k2"], "left"), ["far", "gone"], row, columns, [])
