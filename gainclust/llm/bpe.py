"""Byte-level BPE encoding and decoding by DuckDB queries inside each partition.

A text is cut by the pre-token pattern. Each new pre-token becomes rows (word, position, token); a recursive query
joins neighbouring tokens with the merge table, finds each word's least rank and contracts the leftmost pair of that
rank, until no pair merges. Pre-tokens longer than ``LONG`` bytes run over a table in a loop, so that the recursion's
union of past rows does not pile up. There a step contracts every pair of the least rank within a reach of twice the
longest token that the word's bytes can make, to both sides: merges beyond the reach could touch it only through a
longer token. Of equal ranks the left go first: overlapping pairs count from their run's start, and a contraction that
makes a pair of a smaller rank holds back those to its right. So the steps do not grow with the word's length. Decoding joins ids with the vocabulary and aggregates the bytes in order.

Cases: null or empty text - no ids, empty bytes; lone surrogates cannot occur in Spark strings; special-token strings
are plain text; repeated rows - each encoded; texts of any length are encoded whole; empty table - no rows; other
columns are not read. An id outside the vocabulary raises on decoding.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import held_in_worker, trimmed

CACHE_WORDS = 500_000  # words remembered per worker, in each of two generations; about 200 bytes a word
CHUNK_BYTES = 1 << 19  # bytes of new words per recursive query
TEXT_BYTES = 1 << 21  # bytes of text per step
LONG = 255

#: One contraction of each short word. A pair is packed as rank, position and its right neighbour's position.
SHORT_STEP = """
    near AS (SELECT word, pos, tok, lead(tok) OVER w AS nxt, lead(pos) OVER w AS npos FROM chain WINDOW w AS (PARTITION BY word ORDER BY pos)),
    least AS (SELECT word, min(rank::BIGINT * 65536 + pos * 256 + npos) AS hit FROM near JOIN merges ON a = tok AND b = nxt GROUP BY word),
    nextstate AS (SELECT word, pos, CASE WHEN pos = (hit // 256) % 256 THEN (hit // 65536)::INTEGER ELSE tok END AS tok FROM chain JOIN least USING (word) WHERE pos <> hit % 256)
"""

#: One step for a long word, with the reach put in. A merged pair's token is its rank.
LONG_STEP = """
    pairs AS (SELECT s.pos, s.tok, m.rank FROM (SELECT pos, tok, lead(tok) OVER (ORDER BY pos) AS nxt FROM state) s LEFT JOIN merges m ON m.a = s.tok AND m.b = s.nxt),
    seen AS (SELECT *, coalesce(rank = min(rank) OVER (ORDER BY pos RANGE BETWEEN {reach} PRECEDING AND {reach} FOLLOWING), false) AS least, rank IS DISTINCT FROM lag(rank) OVER (ORDER BY pos) AS begins FROM pairs),
    runs AS (SELECT *, sum(begins::INTEGER) OVER (ORDER BY pos ROWS UNBOUNDED PRECEDING) AS run FROM seen),
    picked AS (SELECT pos, tok, rank, bool_and(least) OVER w AND row_number() OVER w % 2 = 1 AS pick FROM runs WINDOW w AS (PARTITION BY run ORDER BY pos ROWS UNBOUNDED PRECEDING)),
    sided AS (SELECT *, CASE WHEN lag(pick, 2, false) OVER w THEN lag(rank, 2) OVER w ELSE lag(tok) OVER w END AS l, lead(tok, 2) OVER w AS r FROM picked WINDOW w AS (ORDER BY pos)),
    heard AS (SELECT s.pos, s.tok, s.rank, s.pick, s.pick AND (x.rank < s.rank OR y.rank < s.rank) AS loud FROM sided s
        LEFT JOIN merges x ON s.pick AND x.a = s.l AND x.b = s.rank LEFT JOIN merges y ON s.pick AND y.a = s.rank AND y.b = s.r),
    kept AS (SELECT pos, tok, rank, pick AND NOT coalesce(bool_or(loud) OVER (ORDER BY pos RANGE BETWEEN {reach} PRECEDING AND 1 PRECEDING), false) AS pick FROM heard),
    nextstate AS (SELECT pos, CASE WHEN pick THEN rank ELSE tok END AS tok, pick, lag(pick, 1, false) OVER (ORDER BY pos) AS gone FROM kept)
"""


class Codec:
    """Merge table, word cache and the DuckDB connection of one Python worker."""

    def __init__(self, vocabulary: bytes, pattern: str, cache_words: int = CACHE_WORDS):
        import duckdb
        import regex

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, vocabulary.splitlines()) if a}
        self.ranks, self.find = ranks, regex.compile(pattern).findall
        self.cache_words = cache_words
        self.cache: dict[str, bytes] = {}  # ids as little-endian 32-bit
        self.old: dict[str, bytes] = {}
        self.byte_ids = np.array([ranks[bytes([i])] for i in range(256)], np.int32)
        self.token_bytes = np.frombuffer(b"".join(ranks), np.uint8)
        self.token_sizes = np.fromiter(map(len, ranks), np.int64, len(ranks))
        self.token_ends = np.cumsum(self.token_sizes)
        a, b, rank = [], [], []
        for token, r in ranks.items():
            for cut in range(1, len(token)):
                x, y = ranks.get(token[:cut]), ranks.get(token[cut:])
                if x is not None and y is not None:
                    a.append(x), b.append(y), rank.append(r)
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": "200MB"})
        self.db.execute("SET preserve_insertion_order = false")
        self.db.execute("SET temp_directory = ''")  # nothing goes to a local folder
        merges = pa.table({"a": pa.array(a, pa.int32()), "b": pa.array(b, pa.int32()), "rank": pa.array(rank, pa.int32())})
        self.db.register("m_", merges)
        self.db.execute("CREATE TABLE merges AS SELECT * FROM m_")
        vocab = pa.table({"id": pa.array(list(ranks.values()), pa.int32()), "bytes": pa.array(list(ranks.keys()), pa.binary())})
        self.db.register("v_", vocab)
        self.db.execute("CREATE TABLE vocab AS SELECT * FROM v_")

    def _start(self, words: list[bytes]) -> pa.Table:
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        flat = np.frombuffer(b"".join(words), np.uint8)
        starts = np.cumsum(sizes) - sizes
        return pa.table({"word": np.repeat(np.arange(len(words), dtype=np.int32), sizes), "pos": (np.arange(len(flat)) - np.repeat(starts, sizes)).astype(np.int32), "tok": self.byte_ids[flat]})

    def contract(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word (none of them empty) as little-endian 32-bit numbers; a long word comes alone."""
        self.db.register("start_", self._start(words))
        if max(map(len, words)) <= LONG:
            got = self.db.sql(f"""
                WITH RECURSIVE chain(step, word, pos, tok) AS (
                    SELECT 0, word, pos, tok FROM start_
                    UNION ALL
                    (WITH {SHORT_STEP} SELECT (SELECT max(step) + 1 FROM chain), word, pos, tok FROM nextstate))
                SELECT step, word, pos, tok FROM chain""").to_arrow_table()
            step, word, pos, tok = (got[c].to_numpy() for c in ("step", "word", "pos", "tok"))
            # the rows of each word's last step, in order
            last = np.zeros(len(words), np.int32)
            np.maximum.at(last, word, step.astype(np.int32))
            keep = np.flatnonzero(step == last[word])
            keep = keep[np.argsort(word[keep].astype(np.int64) << 8 | pos[keep])]
            word, tok = word[keep], tok[keep]
        else:
            reach = 2 * self.longest(words[0])
            self.db.execute("CREATE OR REPLACE TEMP TABLE state AS SELECT pos, tok FROM start_")
            while True:
                self.db.execute(f"CREATE OR REPLACE TEMP TABLE moved AS WITH {LONG_STEP.format(reach=reach)} SELECT pos, tok, pick FROM nextstate WHERE NOT gone")
                more = self.db.execute("SELECT count(*) FROM moved WHERE pick").fetchall()[0][0]
                self.db.execute("CREATE OR REPLACE TEMP TABLE state AS SELECT pos, tok FROM moved")
                if not more:
                    break
            tok = self.db.sql("SELECT tok FROM state ORDER BY pos").to_arrow_table()["tok"].to_numpy()
            word = np.zeros(len(tok), np.int32)
            for name in ("state", "moved"):
                self.db.execute(f"DROP TABLE {name}")
        self.db.unregister("start_")
        ids = tok.astype("<u4").tobytes()
        edge = [0, *(4 * (np.flatnonzero(np.diff(word)) + 1)).tolist(), len(ids)]
        return [ids[a:b] for a, b in zip(edge[:-1], edge[1:])]

    def longest(self, word: bytes) -> int:
        """Bytes of the longest token made of the word's bytes only."""
        letters = np.zeros(256, bool)
        letters[list(set(word))] = True
        strange = np.concatenate([[0], np.cumsum(~letters[self.token_bytes])])
        return int(self.token_sizes[strange[self.token_ends] == strange[self.token_ends - self.token_sizes]].max())

    def learn(self, words: list[str]) -> None:
        """Put the ids of words not seen so far into the cache."""
        todo: list[tuple[str, bytes]] = []
        for w in words:
            raw = w.encode()
            if (whole := self.ranks.get(raw)) is not None:
                self.cache[w] = whole.to_bytes(4, "little")
            else:
                todo.append((w, raw))
        todo.sort(key=lambda x: len(x[1]) > LONG)
        at = 0
        while at < len(todo):
            end, size, long = at, 0, len(todo[at][1]) > LONG
            while end < len(todo) and size < (1 if long else CHUNK_BYTES) and (len(todo[end][1]) > LONG) == long:  # long ones alone
                size += len(todo[end][1])
                end += 1
            part = todo[at:end]
            self.cache.update(zip([w for w, _ in part], self.contract([raw for _, raw in part])))
            at = end

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        words = [self.find(t) if t else [] for t in texts]
        every = set(chain.from_iterable(words))
        new = every.difference(self.cache)
        if len(self.cache) + len(new) > self.cache_words:
            # words used since the last change of generation survive
            self.old, self.cache, new = self.cache, {}, every
        if self.old:
            old = self.old
            self.cache.update((w, old[w]) for w in new if w in old)
        new.difference_update(self.cache)
        if new:
            self.learn(list(new))
        ids = self.cache.__getitem__
        return [np.frombuffer(b"".join(map(ids, w)), "<u4") for w in words]

    def decode(self, ids: list[np.ndarray]) -> list[bytes]:
        """The bytes of each id list."""
        sizes = np.array([len(x) for x in ids])
        flat = np.concatenate(ids).astype(np.int32) if len(ids) else np.empty(0, np.int32)
        rows = pa.table({"doc": np.repeat(np.arange(len(ids), dtype=np.int32), sizes), "pos": np.arange(len(flat), dtype=np.int32), "id": flat})
        self.db.register("ids_", rows)
        got = self.db.sql("SELECT doc, list(bytes ORDER BY pos) AS parts FROM ids_ JOIN vocab USING (id) GROUP BY doc").to_arrow_table()
        self.db.unregister("ids_")
        out = [b""] * len(ids)
        parts = got["parts"].combine_chunks() if got.num_rows else None
        seen = 0
        if parts is not None:
            bounds = parts.offsets.to_numpy()
            values = parts.values.cast(pa.large_binary())
            at = np.frombuffer(values.buffers()[1], np.int64)[values.offset : values.offset + len(values) + 1]
            data = values.buffers()[2]
            for doc, a, b in zip(got["doc"].to_pylist(), bounds[:-1], bounds[1:]):
                out[doc] = data[int(at[a]) : int(at[b])].to_pybytes() if data is not None else b""
                seen += int(b - a)
        if seen != len(flat):
            raise ValueError("an id is not in the vocabulary")
        return out


def codec(vocabulary: bytes, pattern: str, cache_words: int = CACHE_WORDS) -> Codec:
    """One codec per worker process; its cache outlives the task."""
    return held_in_worker((hashlib.sha256(vocabulary + pattern.encode()).digest(), cache_words), lambda: Codec(vocabulary, pattern, cache_words))


#: What encode_decode can return, by name.
COLUMNS = {"n_tokens": "long", "ids": "array<int>", "decoded": "binary", "ids_sha256": "string", "decoded_sha256": "string"}


def encode_decode(docs: DataFrame, vocabulary_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", returns: tuple[str, ...] = ("ids", "decoded"), cache_words: int = CACHE_WORDS) -> DataFrame:
    """Rows of the id and the columns named in returns (see COLUMNS); every text is encoded and decoded again.

    The vocabulary file (about a megabyte, read on the driver) is broadcast; at most 16 MB are allowed.
    """
    with open(vocabulary_path, "rb") as f:
        vocabulary = f.read()
    if len(vocabulary) > 16 << 20:
        raise ValueError("the vocabulary is broadcast and bounded by 16 MB")
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(shared.value, pattern, cache_words)
        for batch in batches:
            size = np.cumsum(batch.column(2).to_numpy(zero_copy_only=False))
            edge = np.searchsorted(size, np.arange(TEXT_BYTES, (size[-1] if len(size) else 0) + TEXT_BYTES, TEXT_BYTES), "right").tolist()
            at = 0
            for end in sorted({max(e, 1) for e in edge} | {batch.num_rows}):
                part = batch.slice(at, end - at)
                at = end
                if not part.num_rows:
                    continue
                ids = own.encode(part.column(1).to_pylist())
                decoded = own.decode(ids)
                sha = lambda xs: pa.array([hashlib.sha256(x).hexdigest() for x in xs], pa.string())
                made = {
                    "n_tokens": lambda: pa.array([len(x) for x in ids], pa.int64()),
                    "ids": lambda: pa.array([x.astype(np.int32) for x in ids], pa.list_(pa.int32())),
                    "decoded": lambda: pa.array(decoded, pa.binary()),
                    "ids_sha256": lambda: sha(ids),
                    "decoded_sha256": lambda: sha(decoded),
                }
                yield pa.RecordBatch.from_arrays([part.column(0), *(made[c]() for c in returns)], names=["id", *returns])
        own.old = {}

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), F.coalesce(F.octet_length(text_col), F.lit(0)).alias("bytes"))
    return slim.mapInArrow(trimmed(run), "id long, " + ", ".join(f"{c} {COLUMNS[c]}" for c in returns))
