"""Toxicity from subword-bag embeddings under a linear softmax.

A word is the mean of the embeddings of its hashed character n-grams and of
itself; a passage of a few words is the mean of its words; a softmax over two
classes reads the passage.  Embeddings and softmax are trained together in
numpy.  A document scores as its worst passage, so a long text is not judged
by its average, and misspellings share n-grams with the words they come from.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import MEMORY, WORD_BYTES, Memory, extended, map_batches, text_slices
from .token_table import split_words
from .words import _BYTE, range_hash


#: Entries of a bag that one step of training works on at a time.
SCRATCH = 1 << 19


@dataclass(frozen=True)
class Settings:
    """``sample`` bounds the labelled documents used for each class; n-grams in less than ``seen`` of them carry nothing; the rest is the model's shape."""

    sample: int = 1000
    buckets: int = 1 << 16
    width: int = 8
    grams: tuple[int, ...] = (3, 4, 5)
    passage: int = 2
    warm: int = 12
    epochs: int = 50
    rate: float = 0.1
    seen: int = 3
    decay: float = 1e-4
    seed: int = 7


def subwords(words: list[str], s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Bucket numbers of the n-grams of all words in order, and how many each word has (its own among them)."""
    coded = [b"<" + w.encode("utf-8", "surrogatepass") + b">" for w in words]
    data = np.frombuffer(b"".join(coded), np.uint8)
    size = np.array([len(x) for x in coded], np.int64)
    first = np.cumsum(size) - size
    values = _BYTE[data]
    owner = np.repeat(np.arange(len(words)), size)
    stop = np.repeat(first + size, size)
    starts, ends, of = [first], [first + size], [np.arange(len(words))]
    for n in s.grams:
        at = np.flatnonzero(np.arange(len(data)) + n <= stop)
        starts.append(at)
        ends.append(at + n)
        of.append(owner[at])
    starts, ends, of = map(np.concatenate, (starts, ends, of))
    order = np.argsort(of, kind="stable")
    ids = (range_hash(values, starts[order], ends[order]) % np.uint64(s.buckets)).astype(np.int32)
    return ids, np.bincount(of, minlength=len(words))


def train(texts: list[str], labels: list[int], s: Settings = Settings()) -> tuple[np.ndarray, float]:
    """Fit on whole texts; returns each bucket's share of the log-odds and the log-odds of an empty passage.

    First every document is the mean of all its words; then each document is
    judged by its worst passage, as in scoring.  Classes weigh the same.
    """
    split = [[w for w in split_words(t.lower()) if w] for t in texts]
    y = np.array(labels, float)
    full = np.array([len(x) > 0 for x in split], bool)
    split, y = [x for x, f in zip(split, full) if f], y[full]
    if not len(y) or y.min() == y.max():
        return np.zeros(s.buckets), (0.0 if not len(y) else 4.0 * (2 * y[0] - 1))
    number = {w: i for i, w in enumerate(dict.fromkeys(w for x in split for w in x))}
    names = list(number)
    sliced = [subwords(names[lo : lo + 4096], s) for lo in range(0, len(names), 4096)]
    ids, count = (np.concatenate(x) for x in zip(*sliced))
    del names, sliced
    seq = np.array([number[w] for x in split for w in x], np.int32)
    size = np.array([len(x) for x in split])
    del split
    first = np.cumsum(size) - size
    short = np.minimum(size, s.passage)
    owner = np.repeat(np.arange(len(y)), size)
    begin = np.cumsum(count) - count
    # each document as weights of buckets, in groups of documents, which bounds the scratch arrays
    pairs, often = np.unique(owner * len(number) + seq, return_counts=True)
    held, word_no = pairs // len(number), pairs % len(number)
    del pairs

    def bags() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for lo in range(0, len(y), 16):
            i, j = np.searchsorted(held, [lo, lo + 16])
            word, c = word_no[i:j], count[word_no[i:j]]
            key = np.repeat(held[i:j] * s.buckets, c) + ids[np.repeat(begin[word] - (np.cumsum(c) - c), c) + np.arange(int(c.sum()))]
            key, at = np.unique(key, return_inverse=True)
            yield (key // s.buckets).astype(np.int32), (key % s.buckets).astype(np.int32), np.bincount(at, np.repeat(often[i:j] / (size[held[i:j]] * c), c))

    # first the buckets that enough documents have, then the weights of those alone
    spread = sum(np.bincount(gram, minlength=s.buckets) for _, gram, _ in bags())
    live = (spread >= s.seen).astype(float)[:, None]
    total = int(spread[live[:, 0] > 0].sum())
    bag_doc, bag, bag_weight, end = np.empty(total, np.int32), np.empty(total, np.int32), np.empty(total), 0
    for doc, gram, part in bags():
        on = live[gram, 0] > 0
        begin_at, end = end, end + int(on.sum())
        bag_doc[begin_at:end], bag[begin_at:end], bag_weight[begin_at:end] = doc[on], gram[on], part[on]
    del often, held, word_no
    starts = np.flatnonzero(np.arange(len(seq)) - first[owner] <= (size - short)[owner])  # where a passage may start
    of = owner[starts]
    group = np.cumsum(np.bincount(of, minlength=len(y))) - np.bincount(of, minlength=len(y))
    weight = np.where(y == 1, 0.5 / y.sum(), 0.5 / (len(y) - y.sum()))
    rng = np.random.default_rng(s.seed)
    E, W, b = rng.normal(0, 0.1, (s.buckets, s.width)), rng.normal(0, 0.3, (s.width, 2)), np.zeros(2)
    moments = [[np.zeros_like(p), np.zeros_like(p)] for p in (E, W, b)]
    E *= live
    for epoch in range(1, s.epochs + 1):
        if epoch <= s.warm:
            doc, gram, part = bag_doc, bag, bag_weight
        else:
            score = np.add.reduceat((E @ (W[:, 1] - W[:, 0]))[ids], begin) / count
            run = np.concatenate([[0], np.cumsum(score[seq])])
            means = (run[starts + short[of]] - run[starts]) / short[of]
            high = np.maximum.reduceat(means, group)
            top = np.flatnonzero(means == high[of])
            lo = starts[top[np.searchsorted(of[top], np.arange(len(y)))]]
            used = seq[np.repeat(lo - (np.cumsum(short) - short), short) + np.arange(int(short.sum()))]
            c = count[used]
            gram = ids[np.repeat(begin[used] - (np.cumsum(c) - c), c) + np.arange(int(c.sum()))]
            doc = np.repeat(np.repeat(np.arange(len(y)), short), c)
            part = np.repeat(np.repeat(1.0 / short, short) / c, c)
        cuts = [slice(lo, lo + SCRATCH) for lo in range(0, max(1, len(doc)), SCRATCH)]
        h = np.stack([sum(np.bincount(doc[c], E[gram[c], k] * part[c], len(y)) for c in cuts) for k in range(s.width)], 1)
        z = h @ W + b
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        dz = (p - np.stack([1 - y, y], 1)) * weight[:, None]
        dh = dz @ W.T
        dE = np.stack([sum(np.bincount(gram[c], dh[doc[c], k] * part[c], s.buckets) for c in cuts) for k in range(s.width)], 1)
        for param, grad, (m, v) in zip((E, W, b), (dE * live + s.decay * E, h.T @ dz + 1e-4 * W, dz.sum(0)), moments):
            m += 0.1 * (grad - m)
            v += 0.01 * (grad * grad - v)
            param -= s.rate * (m / (1 - 0.9**epoch)) / (np.sqrt(v / (1 - 0.99**epoch)) + 1e-9)
    return E @ (W[:, 1] - W[:, 0]), float(b[1] - b[0])


class Scorer:
    """Scores of texts from a trained model, with a memory of word scores."""

    def __init__(self, odds: np.ndarray, base: float, s: Settings):
        self.odds, self.base, self.s, self.memory = odds, base, s, Memory(self._score, MEMORY // 3)

    def _score(self, words: list[str]) -> list[float]:
        out: list[float] = []
        for lo in range(0, len(words), 4096):
            ids, count = subwords(words[lo : lo + 4096], self.s)
            out += (np.add.reduceat(self.odds[ids], np.cumsum(count) - count) / count).tolist()
        return out

    def __call__(self, texts: list[str]) -> np.ndarray:
        split = [[w for w in split_words(t.lower()) if w] for t in texts]
        known = self.memory(set().union(*split))
        out = np.empty(len(split))
        for i, words in enumerate(split):
            n = min(len(words), self.s.passage)
            run = np.cumsum([0.0, *map(known.__getitem__, words)])
            worst = (run[n:] - run[: len(run) - n]).max() / n if n else 0.0
            out[i] = 1 / (1 + np.exp(-np.clip(worst + self.base, -40, 40)))
        return out


def held_out(doc_id: str):
    """Documents that no label is taken from: crc32 of the id as text leaves 1 modulo 3."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> tuple[np.ndarray, float]:
    """Train on at most ``s.sample`` labelled documents a class, those with the smallest hash of their id.

    Ids are chosen from the labels alone; only the chosen documents' texts are
    gathered.  An id with both labels counts as toxic; of rows that repeat an id
    the text of the smallest hash counts.  Null ids and other labels do not.
    """
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out("doc_id")).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = [known.where(F.col("toxic") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.sample) for k in (0, 1)]
    rows = chosen[0].unionByName(chosen[1])
    own = docs.select("doc_id", "text").join(F.broadcast(rows), "doc_id")
    sample = own.groupBy("doc_id", "toxic").agg(F.min_by("text", F.xxhash64("text")).alias("text")).select("doc_id", "text", "toxic").repartition(1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = pa.Table.from_batches(batches) if (batches := list(batches)) else None
        texts = sorted(zip(got["doc_id"].to_pylist(), (t or "" for t in got["text"].to_pylist()), got["toxic"].to_pylist())) if got else []
        odds, base = train([t for _, t, _ in texts], [k for _, _, k in texts], s)
        yield pa.RecordBatch.from_arrays([pa.array([odds.tobytes()]), pa.array([base])], ["odds", "base"])

    # the bounded sample is trained on by one task, so the driver gets nothing but the model
    model = map_batches(sample, run, "odds binary, base double").first()
    return (np.frombuffer(model.odds), model.base) if model else (np.zeros(s.buckets), 0.0)


def score(docs: DataFrame, model: tuple[np.ndarray, float], s: Settings = Settings(), *, text_col: str = "text", out: str = "score") -> DataFrame:
    """Adds the score (0 to 1) of every whole text; null and empty texts get that of an empty passage."""
    base = docs.drop(out)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(*shared.value, s)
        for batch in batches:
            for b in text_slices(batch, text_col, WORD_BYTES):
                texts = [t or "" for t in b.column(b.schema.get_field_index(text_col)).to_pylist()]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(scorer(texts))], [*b.schema.names, out])

    return map_batches(base, run, extended(base.schema, f"{out} double"))


THRESHOLD = 0.7


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""
    slim = docs.select("doc_id", "text")
    scored = score(slim, fit(slim, labels))
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
