"""Toxicity: subword-bag embeddings averaged into a linear softmax, trained jointly in numpy.

A word's vector is the mean of the vectors of its character n-grams (3 to 5, with word ends marked) and of itself, so
an unseen misspelling shares most of its vector with the word it comes from. The vectors of the words of a window are
averaged (a repeated word counts once) and go through a linear softmax; vectors and softmax are trained together by gradient steps. Windows of
WINDOW words cover the whole text, and a text is as toxic as its most toxic window: one insult in a long text is not
averaged away.

Training uses at most `per_class` labelled toxic texts and CLEAN_SHARE times as many clean ones (a documented bound), chosen by a hash of doc_id among
rows whose crc32(doc_id as text) mod 5 is not 0, whole texts each. A part of the windows is repeated with random
misspellings. The threshold is then set on training texts kept from the fit, so that 0.5 separates whole texts.

Once trained, a word adds a plain number to a window (its mean n-gram vector times the softmax row), so texts are
scored by one cached look-up a word, windows of many texts at once. Defined cases: null and empty texts have no window and score near 0; repeated
rows score alike; very long words have as many n-grams as letters; extra columns are ignored by `score_documents` and
kept by `keep_clean`; with no label of both classes every score is 0.
"""

from __future__ import annotations

import random
from array import array
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS = 17
BUCKETS = 1 << BITS
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: Words of a window: when scoring and in later passes, and in the first pass.
WINDOW, FIRST_WINDOW = 12, 24
DIM = 8
#: Clean training texts for each toxic one.
CLEAN_SHARE = 2
#: Words that a task remembers, and characters of the texts that it scores together.
CACHE_ENTRIES, TOGETHER = 200_000, 400_000
_STRIP = "".join(map(chr, [*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]))


def grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(bucket numbers, owners): of every n-gram of each word and of the word itself, for all words at once.

    A gram is its bytes packed into one number; the owner of a bucket number is the word's place in the list.
    """
    raw = [f"<{w}>".encode() for w in words]
    size = np.fromiter(map(len, raw), np.int64, len(raw))
    x = np.frombuffer(b"".join(raw), np.uint8).astype(np.uint64)
    start = np.cumsum(size) - size
    owner = np.repeat(np.arange(len(raw)), size)
    at = np.arange(len(x)) - start[owner]
    left = size[owner] - at
    buckets, owners, code = [], [], x.copy()
    for n in (2, 3, 4, 5):
        code = code[:-1] | x[n - 1 :] << np.uint64(8 * (n - 1))
        if n > 2:
            whole = left[: len(code)] >= n
            buckets.append(_bucket(code[whole] + np.uint64(n << 40)))
            owners.append(owner[: len(code)][whole])
    if len(raw):
        power = np.cumprod(np.full(int(size.max()), _ODD), dtype=np.uint64)
        buckets.append(_bucket(np.add.reduceat((x + np.uint64(1)) * power[at], start)))
        owners.append(np.arange(len(raw)))
    return np.concatenate(buckets), np.concatenate(owners)


def _bucket(code: np.ndarray) -> np.ndarray:
    return ((code * _ODD) >> np.uint64(64 - BITS)).astype(np.int64)


def blocks(words: list[str], size: int = 16_384) -> Iterator[list[str]]:
    """`grams` takes some hundred bytes a letter while it runs, so long lists go through it in blocks."""
    for at in range(0, len(words), size):
        yield words[at : at + size]


def word_values(weight: np.ndarray, words: list[str]) -> np.ndarray:
    """Mean weight of each word's buckets."""
    out = [np.zeros(0)]
    for block in blocks(words):
        bucket, owner = grams(block)
        out.append(np.bincount(owner, weight[bucket], len(block)) / np.bincount(owner, minlength=len(block)))
    return np.concatenate(out)


def text_words(text: str) -> list[str]:
    return text.lower().split()


def core(chunk: str) -> str:
    return chunk.strip(_STRIP) or chunk


def window_starts(n_words: int, size: int) -> list[int]:
    """Starts of the windows; a last one of under half a window joins the one before."""
    starts = list(range(0, n_words, size))
    return starts[:-1] if len(starts) > 1 and n_words - starts[-1] < size // 2 else starts


def misspell(word: str, rng: random.Random) -> str:
    if len(word) < 4:
        return word
    k = rng.randrange(1, len(word) - 1)
    how = rng.randrange(5)
    if how == 0:
        return word[:k] + word[k + 1 :]
    if how == 1:
        return word[:k] + word[k] + word[k:]
    if how == 2:
        return word[: k - 1] + word[k] + word[k - 1] + word[k + 1 :]
    if how == 3:
        return word[:k] + rng.choice("abcdefghijklmnopqrstuvwxyz") + word[k + 1 :]
    return word.translate(str.maketrans("aeiost", "4310$7"))


@dataclass
class Model:
    #: Each bucket's share of the toxic-over-clean logit.
    weight: np.ndarray
    bias: float
    #: Logit of a whole text at which the score is 0.5.
    threshold: float

    def scorer(self) -> "Scorer":
        return Scorer(self)


class _Numbers(dict):
    """Numbers words in the order in which they are first asked for; `fresh` holds those without a value yet."""

    def __init__(self):
        self.fresh: list[str] = []

    def __missing__(self, word: str) -> int:
        k = self[word] = len(self)
        self.fresh.append(word)
        return k


class Scorer:
    """Scores texts with a bounded memory of words' values. All windows of many texts are one matrix of word numbers."""

    #: A last window of under half a window joins the one before.
    WIDTH = WINDOW + WINDOW // 2 - 1

    def __init__(self, model: Model):
        self.model = model
        self.forget()

    def forget(self) -> None:
        self.numbers, self.values = _Numbers(), np.zeros(1)

    def logits(self, texts: list[str]) -> np.ndarray:
        if len(self.numbers) > CACHE_ENTRIES:
            self.forget()
        lists = [text_words(t) for t in texts]
        n = np.fromiter(map(len, lists), np.int64, len(lists))
        total = int(n.sum())
        out = np.full(len(lists), self.model.bias - 10.0)
        if not total:
            return out
        ids = np.fromiter(map(self.numbers.__getitem__, chain.from_iterable(lists)), np.int32, total)
        del lists
        if self.numbers.fresh:
            # the last place holds the value of no word
            self.values = np.concatenate([self.values[:-1], word_values(self.model.weight, [core(w) for w in self.numbers.fresh]), [0.0]])
            self.numbers.fresh.clear()
        some = n > 0
        n = n[some]
        windows = np.maximum(1, n // WINDOW + (n % WINDOW >= WINDOW // 2))
        first = np.cumsum(windows) - windows
        at = np.arange(total) - np.repeat(np.cumsum(n) - n, n)
        window = np.minimum(at // WINDOW, np.repeat(windows - 1, n))
        grid = np.full((int(windows.sum()), self.WIDTH), -1, np.int32)
        grid[window + np.repeat(first, n), at - WINDOW * window] = ids
        grid.sort(axis=1)
        grid[:, 1:][grid[:, 1:] == grid[:, :-1]] = -1  # a repeated word counts once
        value = self.values[grid].sum(axis=1) / np.maximum((grid >= 0).sum(axis=1), WINDOW)
        out[some] = np.maximum.reduceat(value, first) + self.model.bias
        return out

    def scores(self, texts: list[str]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(texts) - self.model.threshold, -30, 30)))


class Windows:
    """Training windows: word numbers one after another, where each window begins, and its label."""

    def __init__(self):
        self.vocab: dict[str, int] = {}
        self.ids, self.first, self.label = array("i"), array("q"), array("b")

    def add(self, words: list[str], label: int) -> None:
        self.first.append(len(self.ids))
        self.label.append(label)
        self.ids.extend(self.vocab.setdefault(w, len(self.vocab)) for w in dict.fromkeys(words))

    def add_text(self, words: list[str], label: int, size: int, rng: random.Random) -> None:
        bounds = [*window_starts(len(words), size), len(words)]
        for a, b in zip(bounds, bounds[1:], strict=False):
            self.add(words[a:b], label)
            if rng.random() < 0.25:
                self.add([misspell(w, rng) if rng.random() < 0.5 else w for w in words[a:b]], label)


def _distinct(x: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct values, place of each x among them) of numbers under `most`."""
    place = np.zeros(most, np.int64)
    place[x] = 1
    found = np.flatnonzero(place)
    place[found] = np.arange(len(found))
    return found, place.take(x)


def fit(windows: Windows, updates: int, rate: float = 0.15, seed: int = 1, batch: int = 512) -> tuple[np.ndarray, float]:
    """Vectors and softmax trained together by adaptive gradient steps: (logit share of each bucket, bias)."""
    ids, y = np.array(windows.ids), np.array(windows.label).astype(int)
    first = np.append(np.array(windows.first), len(ids))
    flat, sizes = [], [[0]]
    for block in blocks(list(windows.vocab)):
        bucket, owner = grams(block)
        flat.append(bucket[np.argsort(owner, kind="stable")].astype(np.int32))
        sizes.append(np.bincount(owner, minlength=len(block)))
    flat, ptr = np.concatenate(flat), np.cumsum(np.concatenate(sizes))
    weight_of = np.where(y == 1, len(y) / 2 / max(1, (y == 1).sum()), len(y) / 2 / max(1, (y == 0).sum()))
    gen = np.random.default_rng(seed)
    e, w = gen.normal(0, 0.1, (BUCKETS, DIM)).astype(np.float32), gen.normal(0, 0.1, (2, DIM)).astype(np.float32)
    b = np.zeros(2, np.float32)
    sq_e, sq_w, sq_b = np.full(BUCKETS, 1e-6, np.float32), 1e-6, 1e-6
    for _ in range(updates):
        chosen = gen.integers(0, len(y), min(batch, 4 * len(y)))
        lens = first[chosen + 1] - first[chosen]
        edge = np.concatenate([[0], np.cumsum(lens)[:-1]])
        toks, inv = _distinct(ids[np.repeat(first[chosen] - edge, lens) + np.arange(lens.sum())], len(ptr))
        size = ptr[toks + 1] - ptr[toks]
        starts = np.concatenate([[0], np.cumsum(size)[:-1]])
        g = flat[np.repeat(ptr[toks] - starts, size) + np.arange(size.sum())]
        vec = np.add.reduceat(e.take(g, axis=0), starts, axis=0) / size[:, None]
        padded = np.maximum(lens, WINDOW)  # a short text is padded with words of no weight
        mean = np.add.reduceat(vec.take(inv, axis=0), edge, axis=0) / padded[:, None]
        z = mean @ w.T + b
        z -= z.max(axis=1, keepdims=True)
        p = np.exp(z)
        p /= p.sum(axis=1, keepdims=True)
        p[np.arange(len(chosen)), y[chosen]] -= 1
        d = (p * weight_of[chosen][:, None] / len(chosen)).astype(np.float32)
        back = ((d @ w) / padded[:, None]).take(np.repeat(np.arange(len(chosen)), lens), axis=0)
        grad_w, grad_b = d.T @ mean + 1e-4 * w, d.sum(axis=0)
        grad_word = np.stack([np.bincount(inv, back[:, k], len(toks)) for k in range(DIM)]) / size
        touched, where = _distinct(g, BUCKETS)
        spread = np.repeat(np.arange(len(toks)), size)
        grad_e = np.stack([np.bincount(where, x.take(spread), len(touched)) for x in grad_word], axis=1).astype(np.float32)
        sq_e[touched] += (grad_e**2).mean(axis=1)
        e[touched] -= rate * grad_e / np.sqrt(sq_e[touched])[:, None]
        sq_w, sq_b = sq_w + float((grad_w**2).mean()), sq_b + float((grad_b**2).mean())
        w -= rate * grad_w / np.sqrt(sq_w)
        b -= rate * grad_b / np.sqrt(sq_b)
    return (e @ (w[1] - w[0])).astype(np.float64), float(b[1] - b[0])


def train(texts: list[str], labels: list[int], updates: int = 250, seed: int = 1) -> Model:
    """Three passes. Labels are of whole texts, and most windows of a toxic text are clean: the first pass, on long
    windows, finds which words are toxic; the others, on short ones, take the windows of each text that look most
    toxic so far: an eighth of them from toxic texts, a third (the hardest) from clean ones."""
    rng = random.Random(seed)
    kept = sorted({(t, y) for t, y in zip(texts, labels, strict=True) if t.strip()})
    if len({y for _, y in kept}) < 2:
        return Model(np.zeros(BUCKETS), 0.0, 30.0)
    rng.shuffle(kept)
    # a quarter is kept from the fit and sets the threshold, if it has enough of both classes
    apart = kept[: len(kept) // 4]
    if min(sum(y for _, y in apart), sum(1 - y for _, y in apart)) >= 30:
        kept = kept[len(apart) :]
    else:
        apart = kept
    same: dict[str, str] = {}  # one object for all occurrences of a word
    words = [[same.setdefault(w, w) for w in map(core, text_words(t))] for t, _ in kept]
    long = Windows()
    for ws, (_, y) in zip(words, kept, strict=True):
        long.add_text(ws, y, FIRST_WINDOW, rng)
    weight, bias = fit(long, 2 * updates, seed=seed)
    words_seen = list(long.vocab)
    del long
    for turn in (1, 2):
        value = dict(zip(words_seen, word_values(weight, words_seen).tolist(), strict=True))
        short = Windows()
        for ws, (_, y) in zip(words, kept, strict=True):
            bounds = [*window_starts(len(ws), WINDOW), len(ws)]
            parts = [ws[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]
            # by the most toxic word in the first turn; then by the whole window, as the score does
            parts.sort(key=lambda part: -max(value[w] for w in part) if turn == 1 else -sum(value[w] for w in part) / len(part))
            for part in parts[: max(1, len(parts) // 8)] if y else parts[: max(2, len(parts) // 3)]:
                short.add_text(part, y, WINDOW, rng)
        weight, bias = fit(short, updates, seed=seed + turn)
    model = Model(weight, bias, 0.0)
    model.threshold = best_threshold(model.scorer().logits([t for t, _ in apart]), np.array([y for _, y in apart]))
    return model


def best_threshold(logits: np.ndarray, labels: np.ndarray) -> float:
    """Middle of the widest cut among those with the fewest errors, a false alarm counting as four."""
    order = np.argsort(logits, kind="stable")
    x, y = logits[order], labels[order]
    misses, alarms = np.cumsum(y), (1 - y).sum() - np.cumsum(1 - y)
    cost = misses[:-1] + 4 * alarms[:-1]
    gap = np.diff(x)
    cost = np.where(gap > 0, cost, np.inf)
    if not np.isfinite(cost).any():
        return float(x.max())
    low = np.flatnonzero(cost <= cost.min())
    k = low[np.argmax(gap[low])]
    return float((x[k] + x[k + 1]) / 2)


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.encode(F.coalesce(doc_id.cast("string"), F.lit("")), "UTF-8")) % 5 == 0


def labelled_sample(docs: DataFrame, labels: DataFrame, per_class: int = 1500) -> tuple[list[str], list[int]]:
    """At most per_class whole toxic texts and CLEAN_SHARE times as many clean ones, never of held-out rows; which ones,
    a hash of doc_id decides.

    The classes are counted first; a threshold of the hash then lets about the wanted number through, so that no task
    gets more than a sample. A doc_id with labels of both classes is toxic; of several texts of one doc_id the least
    one is taken.
    """
    usable = labels.select(F.col("doc_id").alias("__rc_id"), F.col("toxic").cast("int").alias("__rc_toxic")).filter(F.col("__rc_id").isNotNull() & F.col("__rc_toxic").isin(0, 1) & ~held_out(F.col("__rc_id")))
    usable = usable.groupBy("__rc_id").agg(F.max("__rc_toxic").alias("__rc_toxic"))
    counts = {r[0]: r[1] for r in usable.groupBy("__rc_toxic").count().collect()}
    place = F.pmod(F.xxhash64("__rc_id"), F.lit(1 << 40))
    chosen = None
    for c in (0, 1):
        want = per_class if c else CLEAN_SHARE * per_class
        share = min(1.0, (want + 5 * want**0.5) / max(1, counts.get(c, 0)))
        part = usable.filter((F.col("__rc_toxic") == c) & (place < int(share * (1 << 40)))).orderBy(place, "__rc_id").limit(want)
        chosen = part if chosen is None else chosen.union(part)
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("__rc_id")).filter(F.col("text").isNotNull())
    found = sorted(tuple(r) for r in rows.groupBy("__rc_id", "__rc_toxic").agg(F.min("text")).collect())
    return [t for _, _, t in found], [y for _, y, _ in found]


def scorer(docs: DataFrame, model: Model):
    """Column function of a text's score. Only texts travel to Python, and only numbers back."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def score(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        scorer = shared.value.scorer()
        for texts in arrays:
            out, held, size = [], [], 0
            for x in texts:
                held.append(x.as_py() or "")
                size += len(held[-1])
                if size >= TOGETHER:
                    out.append(scorer.scores(held))
                    held, size = [], 0
            yield pa.array(np.concatenate([*out, scorer.scores(held)]), pa.float64())

    return score


def score_documents(docs: DataFrame, labels: DataFrame, per_class: int = 1500) -> DataFrame:
    model = train(*labelled_sample(docs, labels, per_class))
    scored = docs.select("doc_id", scorer(docs, model)("text").alias("__rc_score"))
    score = F.col("__rc_score")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), score.alias("score"), (score >= 0.5).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, labels: DataFrame, per_class: int = 1500, source: DataFrame | None = None) -> DataFrame:
    """Documents that score under 0.5, with all their columns. The model learns from `source`, by default `docs`."""
    model = train(*labelled_sample(docs if source is None else source, labels, per_class))
    return docs.filter(scorer(docs, model)("text") < 0.5)
