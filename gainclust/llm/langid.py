"""Language identification by interpolated Kneser-Ney character models in sorted hash arrays.

One model of order five per language, over letters of words set in spaces. For every n-gram the array holds, per
language, the discounted share of its count; for every context the weight handed to the next lower order. The
languages share one sorted array of 64-bit hashes, so one binary search serves all of them. The language of least
cross-entropy per character wins. A fifth of the training sample is left out of the counts and calibrates
(a) the temperature that turns entropies into a score between 0 and 1 and (b) the entropy above which a text is rejected.

Training uses a bounded sample: at most about ``rows_each`` labelled rows per language, drawn by a hash of the id, of
texts up to ``max_chars`` characters (longer ones are left out, never cut), and fewer of each where all together would
exceed about ``total_chars`` characters. Prediction reads every whole text.

Cases: null text or text without a letter - ``und``, score 0, rejected; no usable training row - everything is ``und``;
null languages do not train; ties between languages - the first by name; null id - predicted, hashed as ``null``;
repeated rows - each predicted; empty table - no rows; other columns are not read.
"""

from __future__ import annotations

import re
import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import held_in_worker, trimmed

from gainclust.llm.mixing import row_hash

ORDER, DISCOUNT, ALPHABET = 5, 0.75, 65_536
CACHE_WORDS, TEXTS = 150_000, 512
MAX_LANGUAGES = 256
LETTERS = re.compile(r"[^\W\d_]+")
_MUL = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[str]:
    return LETTERS.findall(text.lower()) if text else []


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _positions(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Code points of ' word ' after one another; word number and place in the word of each predicted character."""
    flat = np.frombuffer("".join(f" {w} " for w in words).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 2
    starts = np.cumsum(sizes) - sizes
    word = np.repeat(np.arange(len(words)), sizes)
    return flat, word, np.arange(len(flat)) - starts[word]


def _gram_keys(flat: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n characters that end at each position (meaningful where that many are in the word)."""
    h = np.full(len(flat), n, np.uint64)
    for back in range(n - 1, -1, -1):
        h = h * _MUL + np.roll(flat, back) + np.uint64(1)
    return _mix(h)


@dataclass
class Model:
    languages: list[str]
    grams: np.ndarray  # sorted hashes of n-grams, and per language the discounted share
    share: np.ndarray
    contexts: np.ndarray  # sorted hashes of contexts, and per language the weight of the lower order
    weight: np.ndarray
    temperature: float = 1.0
    bound: float = float("inf")
    token: str = field(default_factory=lambda: uuid.uuid4().hex)  # names the model within a worker

    def costs(self, words: list[str]) -> np.ndarray:
        """Sum of -log2 p over each word's characters and its end, per language."""
        flat, word, place = _positions(words)
        keep = place > 0
        p = np.full((len(flat), len(self.languages)), 1.0 / ALPHABET)
        for n in range(1, ORDER + 1):
            at = np.flatnonzero(keep & (place >= n - 1))
            context = _find(self.contexts, _gram_keys(np.roll(flat, 1), n - 1)[at]) if n > 1 else np.zeros(len(at), np.int64)
            gram = _find(self.grams, _gram_keys(flat, n)[at])
            w = np.where((context >= 0)[:, None], self.weight[context], 1.0) if n > 1 else self.weight[np.searchsorted(self.contexts, _ROOT)][None, :]
            p[at] = np.where((gram >= 0)[:, None], self.share[gram], 0.0) + w * p[at]
        bits = -np.log2(p[keep])
        first = np.flatnonzero(np.diff(word[keep], prepend=-1))
        return np.add.reduceat(bits, first, axis=0)


_ROOT = np.uint64(0)  # hash of the empty context


def _find(sorted_keys: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Index of each key, or -1."""
    at = np.minimum(np.searchsorted(sorted_keys, keys), max(len(sorted_keys) - 1, 0))
    return np.where(sorted_keys[at] == keys, at, -1)


def _counts(words: list[str], times: np.ndarray) -> tuple[dict[str, np.ndarray], dict[str, np.ndarray]]:
    """Shares by n-gram and weights by context of one language."""
    flat, word, place = _positions(words)
    keep, times = place > 0, times[word].astype(np.float64)
    grams, shares, contexts, weights = [], [], [], []
    for n in range(1, ORDER + 1):
        keys = _gram_keys(flat, n)
        before = _gram_keys(np.roll(flat, 1), n - 1) if n > 1 else np.full(len(flat), _ROOT)
        # n-grams of the highest order, and those that reach back to the word's start, count as often as they occur
        top = keep & ((place == n - 1) if n < ORDER else (place >= n - 1))
        g, first, which = np.unique(keys[top], return_index=True, return_inverse=True)
        parts = [(g, np.bincount(which, times[top], len(g)), before[top][first])]
        if n < ORDER:
            # the others count once for each different character before them
            inner = np.flatnonzero(keep & (place >= n))
            _, kinds = np.unique(_gram_keys(flat, n + 1)[inner], return_index=True)
            inner = inner[kinds]
            g, first, which = np.unique(keys[inner], return_index=True, return_inverse=True)
            parts.append((g, np.bincount(which, minlength=len(g)).astype(np.float64), before[inner][first]))
        g, c, h = (np.concatenate(x) for x in zip(*parts))
        g, first, which = np.unique(g, return_index=True, return_inverse=True)
        c, h = np.bincount(which, c, len(g)), h[first]
        ctx, which = np.unique(h, return_inverse=True)
        total, kinds = np.bincount(which, c), np.bincount(which)
        d = np.minimum(DISCOUNT, c)
        grams.append(g), shares.append((c - d) / total[which])
        contexts.append(ctx), weights.append(np.bincount(which, d) / total)
    return dict(zip(("k", "v"), map(np.concatenate, (grams, shares)))), dict(zip(("k", "v"), map(np.concatenate, (contexts, weights))))


def _merged(parts: list[dict[str, np.ndarray]], missing: float) -> tuple[np.ndarray, np.ndarray]:
    keys = np.unique(np.concatenate([p["k"] for p in parts]))
    out = np.full((len(keys), len(parts)), missing, np.float32)
    for i, p in enumerate(parts):
        out[np.searchsorted(keys, p["k"]), i] = p["v"]
    return keys, out


def fit(texts: list[str], langs: list[str], folds: list[bool]) -> Model | None:
    """Model from labelled texts; rows with fold True calibrate and are not counted."""
    languages = sorted({x for x, t, f in zip(langs, texts, folds) if not f and words_of(t)})
    if not languages:
        return None
    counts = {x: Counter() for x in languages}
    for t, x, f in zip(texts, langs, folds):
        if not f and x in counts:
            counts[x].update(words_of(t))
    parts = [_counts(list(c), np.fromiter(c.values(), np.int64, len(c))) for c in counts.values()]
    model = Model(languages, *_merged([p[0] for p in parts], 0.0), *_merged([p[1] for p in parts], 1.0))
    # calibration
    scorer = Scorer(model)
    held = [(t, languages.index(x)) for t, x, f in zip(texts, langs, folds) if f and x in counts and words_of(t)]
    if held:
        entropy, n = scorer.entropies([t for t, _ in held])
        truth = np.array([x for _, x in held])
        grid = [2.0**i for i in range(-4, 9)]
        loss = [-np.log(np.maximum(_posterior(entropy, t)[np.arange(len(truth)), truth], 1e-12)).mean() for t in grid]
        model.temperature = grid[int(np.argmin(loss))]
        long = n >= 50
        if long.any():
            model.bound = float(np.quantile(entropy.min(1)[long], 0.999)) * 1.5
    return model


def _posterior(entropy: np.ndarray, temperature: float) -> np.ndarray:
    z = np.exp(-(entropy - entropy.min(1, keepdims=True)) * temperature)
    return z / z.sum(1, keepdims=True)


class Scorer:
    """A model with a cache of word costs in two generations."""

    def __init__(self, model: Model):
        self.model = model
        self.rows: dict[str, int] = {}
        self.costs = np.empty((0, len(model.languages)), np.float32)

    def entropies(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Bits per character (texts x languages) and the number of letters; 0 letters: entropy 0."""
        words = [words_of(t) for t in texts]
        every = set().union(*words)
        new = [w for w in every if w not in self.rows]
        if len(self.rows) + len(new) > CACHE_WORDS:
            kept = [w for w in every if w in self.rows]
            self.costs = self.costs[[self.rows[w] for w in kept]]
            self.rows = {w: i for i, w in enumerate(kept)}
        if new:
            new.sort()
            found = [self.model.costs(new[a : a + 20_000]) for a in range(0, len(new), 20_000)]
            self.rows |= {w: i + len(self.costs) for i, w in enumerate(new)}
            self.costs = np.concatenate([self.costs, *(x.astype(np.float32) for x in found)])
        at = self.rows.__getitem__
        sums = np.zeros((len(texts), len(self.model.languages)))
        for i, w in enumerate(words):
            if w:
                sums[i] = self.costs[list(map(at, w))].sum(0, dtype=np.float64)
        letters = np.array([sum(map(len, w)) for w in words])
        chars = letters + np.array([len(w) for w in words])
        return sums / np.maximum(chars, 1)[:, None], letters


def sample(docs: DataFrame, rows_each: int, max_chars: int, total_chars: int, id_col: str, text_col: str, lang_col: str) -> DataFrame:
    """Bounded training rows (lang, text, fold), drawn by a hash of the id."""
    h = row_hash(F.col(id_col), 7)
    usable = docs.select(F.col(text_col).alias("text"), F.col(lang_col).alias("lang"), h.alias("h")).where("lang IS NOT NULL AND text IS NOT NULL").where(F.length("text") <= max_chars)
    sizes = usable.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).alias("chars")).limit(MAX_LANGUAGES + 1).collect()
    if len(sizes) > MAX_LANGUAGES:
        raise ValueError(f"over {MAX_LANGUAGES} languages")
    every = sum(min(1.0, rows_each / r.n) * r.chars for r in sizes)
    part = min(1.0, total_chars / max(every, 1))
    limit = F.lit(0)
    for r in sizes:
        limit = F.when(F.col("lang") == r.lang, int(part * min(1.0, rows_each / r.n) * 2**48)).otherwise(limit)
    return usable.where(F.col("h") < limit).select("lang", "text", (F.col("h") % 5 == 0).alias("fold"))


def train(docs: DataFrame, rows_each: int = 800, max_chars: int = 20_000, total_chars: int = 100_000_000, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model | None:
    got = sample(docs, rows_each, max_chars, total_chars, id_col, text_col, lang_col).toArrow().to_pydict()
    order = sorted(range(len(got["text"])), key=lambda i: (got["lang"][i], got["text"][i]))
    return fit(*[[got[c][i] for i in order] for c in ("text", "lang", "fold")])


OUT = "id long, lang_pred string, score double, entropy double, rejected boolean"


def identify(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text", keep: list[Column] | None = None) -> DataFrame:
    """Rows (id, lang_pred, score, entropy, rejected). rejected: no letter, or entropy over the calibrated bound.

    keep: further columns to carry, named apart from those above.
    """
    spark = docs.sparkSession
    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), *(keep or []))
    carried = slim.columns[2:]
    shared = spark.sparkContext.broadcast(model)  # bounded by the training sample
    schema = OUT + "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in slim.schema.fields[2:])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        scorer = held_in_worker(m.token, lambda: Scorer(m)) if m is not None else None
        for batch in batches:
            for a in range(0, batch.num_rows, TEXTS):
                part = batch.slice(a, TEXTS)
                n = part.num_rows
                pred, score, entropy = ["und"] * n, np.zeros(n), np.zeros(n)
                reject = np.ones(n, bool)
                if m is not None:
                    e, letters = scorer.entropies(part.column(1).to_pylist())
                    best, some = e.argmin(1), letters > 0
                    pred = [m.languages[b] if s else "und" for b, s in zip(best, some)]
                    score = np.where(some, _posterior(e, m.temperature).max(1), 0.0)
                    entropy = np.where(some, e.min(1), 0.0)
                    reject = ~some | (entropy > m.bound)
                cols = [part.column(0), pa.array(pred), pa.array(score), pa.array(entropy), pa.array(reject), *(part.column(i + 2) for i in range(len(carried)))]
                yield pa.RecordBatch.from_arrays(cols, names=["id", "lang_pred", "score", "entropy", "rejected", *carried])

    return slim.mapInArrow(trimmed(run), schema)
