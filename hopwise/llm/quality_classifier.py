"""A quality classifier on learned subword embeddings.

A word is the run between white space. Its vector is the mean of learned vectors in a hash table of buckets:
one for the word, one for each character n-gram of ``<word>``. Runs of two and three words have a learned vector
each, in a hash table of their own that starts at zero, so that a run never seen in training says nothing. Besides,
two equal words at a distance of one to ``BACK`` words share a vector by the distance alone. A document's vector is
the mean over its words, runs of words and equal pairs; a softmax over two classes reads it. Everything is trained
by stochastic gradient descent in numpy, on a bounded
sample: of the labelled rows with crc32(doc_id as text) mod 3 other than 1, those with the least hash of the
id, at most ``per_class`` of each label. All other rows of that kind, and all held-out rows, are never seen.
Labels enter through the sample alone; lang, source and doc_id are never inputs of a score.

With fixed weights the logit is linear in the mean, so scoring a word or a run means adding one number; a bounded
cache keeps those of words. Every document is scored over its whole text in one pass over the table, without a shuffle.
Null and empty texts have the zero vector, and so the score of the bias. A null label is no label; an id with
labels that differ takes each as a row. Without any labelled row, or with one class alone, scores are the
smoothed share of the classes. Ties in the sample's order are broken by the id; rows that repeat score alike.
"""

from __future__ import annotations

import re
import zlib
from array import array
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_as_string, id_back, mixed

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
BACK = 6
#: bytes of the n-grams of ``<word>``
N_GRAMS = (3, 4)


def buckets_of(word: str, buckets: int) -> list[int]:
    """The buckets of a word and its n-grams; ``buckets`` is a power of two."""
    data, mask, crc = f"<{word}>".encode("utf-8", "surrogatepass"), buckets - 1, zlib.crc32
    return [crc(data, 7) & mask, *[crc(data[i : i + n], n) & mask for n in N_GRAMS for i in range(len(data) - n + 1)]]


class WordTable(dict):
    """word -> its number; ``hashes`` and ``scores`` by number. Emptied between texts when full, so its size is bounded."""

    def __init__(self, line: np.ndarray | None = None, buckets: int = 0, most: int = 300_000):
        super().__init__()
        self.line, self.buckets, self.most = None if line is None else line.tolist(), buckets, most
        self.hashes, self.scores = array("Q"), array("d")

    def __missing__(self, word: str) -> int:
        at = self[word] = len(self)
        self.hashes.append(xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass")))
        if self.line is not None:
            found = buckets_of(word, self.buckets)
            self.scores.append(sum(map(self.line.__getitem__, found)) / len(found))
        return at

    def of(self, words: list[str]) -> np.ndarray:
        if len(self) >= self.most:
            self.clear()
            self.hashes, self.scores = array("Q"), array("d")
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


def runs_of(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """The buckets of the runs of two and of three words."""
    step, mask = np.uint64(0x100000001B3), np.uint64(buckets - 1)
    two = mixed(hashes[:-1] * step + hashes[1:])
    three = mixed(two[:-1] * step + hashes[2:])
    return (np.concatenate([two, three]) & mask).astype(np.int64)


def repeats_of(at: np.ndarray) -> np.ndarray:
    """How many words equal the word k before, for k from 1 to BACK."""
    return np.array([np.count_nonzero(at[k:] == at[:-k]) for k in range(1, BACK + 1)])


@dataclass
class SubwordModel:
    vectors: np.ndarray  # buckets of words and characters, BACK rows, as many buckets of runs
    weights: np.ndarray  # 2 x dimensions
    bias: np.ndarray  # 2

    @property
    def buckets(self) -> int:
        return (len(self.vectors) - BACK) // 2

    def features(self, text: str | None, table: WordTable, cache: dict) -> tuple[np.ndarray, np.ndarray]:
        """Rows of ``vectors`` and the share of each in the document's mean."""
        words = WORDS.findall(text or "")
        if not words:
            return np.zeros(0, np.int64), np.zeros(0, np.float32)
        at = table.of(words)
        repeats, runs = repeats_of(at), runs_of(np.frombuffer(table.hashes, np.uint64)[at], self.buckets)
        total = len(words) + len(runs) + int(repeats.sum())
        shares = {self.buckets + k: n / total for k, n in enumerate(repeats.tolist())}
        for w, n in Counter(words).items():
            if w not in cache:
                cache[w] = buckets_of(w, self.buckets)
            for b in cache[w]:
                shares[b] = shares.get(b, 0.0) + n / (len(cache[w]) * total)
        for b, n in Counter(runs.tolist()).items():
            shares[self.buckets + BACK + b] = n / total
        return np.fromiter(shares.keys(), np.int64, len(shares)), np.fromiter(shares.values(), np.float32, len(shares))

    def line(self) -> tuple[np.ndarray, float]:
        """The logit of class 1 as one number per row of ``vectors``, and the bias."""
        return self.vectors @ (self.weights[1] - self.weights[0]), float(self.bias[1] - self.bias[0])


def train(rows: list[tuple[str | None, int]], buckets: int = 1 << 17, dimensions: int = 8, epochs: int = 8, rate: float = 4.0, seed: int = 11) -> SubwordModel:
    """Stochastic gradient descent, one document at a step, with a rate that falls to nothing."""
    rng = np.random.default_rng(seed)
    drawn = rng.uniform(-1, 1, (buckets + BACK, dimensions)).astype(np.float32) / dimensions
    model = SubwordModel(np.concatenate([drawn, np.zeros((buckets, dimensions), np.float32)]), np.zeros((2, dimensions), np.float32), np.zeros(2, np.float32))
    counts = np.bincount([y for _, y in rows], minlength=2)[:2] if rows else np.zeros(2, int)
    model.bias[:] = np.log((counts + 1) / (counts.sum() + 2))
    if (counts == 0).any():
        return model
    table, cache = WordTable(), {}
    data = [(*model.features(text, table, cache), y) for text, y in rows]
    step, steps = 0, epochs * len(data)
    for _ in range(epochs):
        for k in rng.permutation(len(data)):
            ids, shares, y = data[k]
            now = rate * (1 - step / steps)
            step += 1
            hidden = shares @ model.vectors[ids]
            z = model.weights @ hidden + model.bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y] -= 1
            back = p @ model.weights
            model.weights -= now * np.outer(p, hidden)
            model.bias -= 0.05 * now * p
            model.vectors[ids] -= (now * shares)[:, None] * back[None, :]  # ids are distinct
    return model


def held_out(doc_id: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, per_class: int) -> list[tuple[str | None, int]]:
    """At most ``per_class`` rows of each label: the broadcast and what the driver gets have that bound."""
    known = labels.select("doc_id", F.col("quality").cast("int").alias("y")).where(F.col("y").isin(0, 1) & ~held_out())
    chosen = None
    for y in (0, 1):
        one = known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
        chosen = one if chosen is None else chosen.unionByName(one)
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    rows = texts.orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(2 * per_class).collect()
    return [(r["text"], r["y"]) for r in rows]


def score_texts(texts, table: WordTable, back: np.ndarray, of_runs: np.ndarray, bias: float) -> np.ndarray:
    out = np.empty(len(texts))
    for i, text in enumerate(texts):
        words = WORDS.findall(text) if text else []
        logit = bias
        if words:
            at = table.of(words)
            repeats, runs = repeats_of(at), runs_of(np.frombuffer(table.hashes, np.uint64)[at], len(of_runs))
            total = len(words) + len(runs) + int(repeats.sum())
            logit += (np.frombuffer(table.scores, np.float64)[at].sum() + of_runs[runs].sum() + repeats @ back) / total
        out[i] = 1 / (1 + np.exp(-np.clip(logit, -60, 60)))
    return out


def classify(docs: DataFrame, labels: DataFrame, per_class: int = 500, **training) -> DataFrame:
    """doc_id, held_out, score, predicted: a row per row of ``docs(doc_id, text)``."""
    model = train(training_rows(docs, labels, per_class), **training)
    line, bias = model.line()
    shared = docs.sparkSession.sparkContext.broadcast((line.astype(np.float64), model.buckets, bias))  # as large as the model

    def score(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        line, buckets, bias = shared.value
        table = WordTable(line[:buckets], buckets)
        for frame in frames:
            scores = score_texts(frame["text"].tolist(), table, line[buckets : buckets + BACK], line[buckets + BACK :], bias)
            yield pd.DataFrame({"doc_id": frame["doc_id"], "score": scores})

    scored = docs.select(id_as_string(docs, "doc_id"), "text").mapInPandas(score, "doc_id string, score double")
    return scored.select(id_back(docs, "doc_id"), held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
