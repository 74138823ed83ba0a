"""Benchmark decontamination: a prefix-filtered join of document texts with item-sized windows.

Words are lower-cased runs of ASCII letters, digits and all characters beyond ASCII. A window is ``size``
consecutive words of an item (a shorter item, if it has a word, is one window). Windows and documents are sets of
shingles, runs of up to ``SHINGLE`` words, with their places. A document holds a window only if it has all shingles
of it, so with shingles in the order of rarity one is the necessary prefix: the rarest. How often the corpus shows
each of the benchmark's shingles is counted in a first pass, over all documents. Then a document shingle that is
some window's prefix joins, and its place in the window gives the one start that is possible (positional bound);
the start must leave room for the whole window (length bound); last, the window is compared word by word.

Bounded memory: windows travel to executors in blocks of at most about ``block_windows`` windows (some 200 bytes
each), whatever the size of the benchmark, and the driver holds two blocks at most; each block is matched against all
documents. With one block nothing of the documents is shuffled; with more, each block's spans are written, and
united for each document.

Null and empty texts have no words. Rows that repeat give equal rows; equal items each count by item_id; a
null item_id counts as the empty string; an empty benchmark leaves zero hits, an empty table an empty table.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_as_string, id_back, written

#: over UTF-8: bytes from 0x80 up belong to characters beyond ASCII, and lower() of bytes changes A-Z alone
WORDS = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
SHINGLE = 3


def words_of(text: str | None) -> list[bytes]:
    return WORDS.findall(text.encode("utf-8", "surrogatepass").lower()) if text else []


def windows_of(words: list[bytes], size: int) -> list[tuple[bytes, ...]]:
    if len(words) <= size:
        return [tuple(words)] if words else []
    return [tuple(words[i : i + size]) for i in range(len(words) - size + 1)]


class Numbered:
    """The words of some windows as numbers from 1; any other word is 0. Shingles of them are exact 64-bit numbers."""

    def __init__(self, number: dict[bytes, int]):
        self.number, self.base = number, len(number) + 1
        if self.base**SHINGLE >= 2**63:
            raise ValueError("too many words in one block of windows")

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.number.get, words, repeat(0)), np.int64, len(words))

    def shingles(self, numbers: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Places and keys of the runs of ``k`` words that are all known."""
        n = max(0, len(numbers) - k + 1)
        key, known = numbers[:n], numbers[:n] > 0
        for i in range(1, k):
            part = numbers[i : i + n]
            key, known = key * self.base + part, known & (part > 0)
        places = np.flatnonzero(known)
        return places, key[places]


@dataclass
class Block:
    """Windows of some items, each with the numbers of the items that have it, and the items' ids."""

    windows: list[tuple[tuple[bytes, ...], list[int]]]
    ids: list[str]

    def __post_init__(self):
        number: dict[bytes, int] = {}
        for window, _ in self.windows:
            for word in window:
                number.setdefault(word, len(number) + 1)
        self.words = Numbered(number)
        self.shingles: dict[int, list] = defaultdict(list)  # length -> (window, its shingles by place)
        for i, (window, _) in enumerate(self.windows):
            k = min(SHINGLE, len(window))
            self.shingles[k].append((i, self.words.shingles(self.words.of(list(window)), k)[1]))

    def vocabulary(self) -> dict[int, np.ndarray]:
        return {k: np.unique(np.concatenate([x for _, x in rows])) for k, rows in self.shingles.items()}

    def prefixes(self, counts: dict[tuple[int, int], int]) -> dict[int, tuple[np.ndarray, dict[int, list]]]:
        """length -> sorted prefix shingles, and shingle -> [(its place, window words, items)]: the rarest of each window."""
        out = {}
        for k, rows in self.shingles.items():
            by: dict[int, list] = defaultdict(list)
            for i, x in rows:
                place = min(range(len(x)), key=lambda p: (counts.get((k, int(x[p])), 0), int(x[p]), p))  # noqa: B023
                window, items = self.windows[i]
                by[int(x[place])].append((place, list(window), items))
            out[k] = (np.array(sorted(by), np.int64), dict(by))
        return out


def among(values: np.ndarray, sorted_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which of ``values`` are in ``sorted_``, and where there."""
    at = np.searchsorted(sorted_, values)
    at[at == len(sorted_)] = 0
    hit = np.flatnonzero(sorted_[at] == values)
    return hit, at[hit]


def corpus_counts(docs: DataFrame, words: Numbered, vocabulary: dict[int, np.ndarray]) -> DataFrame:
    """k, shingle, n: how often the corpus shows each shingle of the vocabulary; sums are made before the shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast((words, vocabulary))

    def count(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words, vocabulary = shared.value
        seen = {k: np.zeros(len(v), np.int64) for k, v in vocabulary.items()}
        for frame in frames:
            for text in frame["text"]:
                numbers = words.of(words_of(text))
                for k, v in vocabulary.items():
                    _, x = words.shingles(numbers, k)
                    if len(x):
                        np.add.at(seen[k], among(x, v)[1], 1)
        for k, v in vocabulary.items():
            met = seen[k] > 0
            yield pd.DataFrame({"k": k, "shingle": v[met], "n": seen[k][met]})

    return docs.select("text").mapInPandas(count, "k int, shingle long, n long").groupBy("k", "shingle").agg(F.sum("n").alias("n"))


def matches(words: list[bytes], known: Numbered, prefixes: dict[int, tuple[np.ndarray, dict[int, list]]]) -> tuple[list[tuple[int, int]], set[int]]:
    """Merged spans [start, end) of hit words, and the numbers of the items met."""
    found: list[tuple[int, int]] = []
    items: set[int] = set()
    n, numbers = len(words), known.of(words)
    for k, (sorted_, by) in prefixes.items():
        places, x = known.shingles(numbers, k)
        for i in among(x, sorted_)[0].tolist() if len(x) else ():
            at = int(places[i])
            for place, window, of in by[int(x[i])]:
                start = at - place
                end = start + len(window)
                if start >= 0 and end <= n and words[start:end] == window:
                    found.append((start, end))
                    items.update(of)
    spans: list[list[int]] = []
    for start, end in sorted(found):
        if spans and start <= spans[-1][1]:
            spans[-1][1] = max(end, spans[-1][1])
        else:
            spans.append([start, end])
    return [tuple(x) for x in spans], items


def blocks_of(benchmark: DataFrame, size: int, block_windows: int) -> Iterator[Block]:
    """Blocks of windows, read item by item; an item with very many is in several."""
    windows: dict[tuple[bytes, ...], list[int]] = {}
    ids: list[str] = []
    for row in benchmark.select(F.col("item_id").cast("string").alias("i"), "text").toLocalIterator():
        ids.append(row["i"] or "")
        for window in set(windows_of(words_of(row["text"]), size)):
            windows.setdefault(window, []).append(len(ids) - 1)
            if len(windows) >= block_windows:
                yield Block(list(windows.items()), ids)
                windows, ids = {}, [row["i"] or ""]
    if windows:
        yield Block(list(windows.items()), ids)


def find_matches(rows: DataFrame, block: Block | None) -> DataFrame:
    """key, n_words, spans (array of start, end), items (array of ids) for ``rows(key, text)``, the key a string."""
    spark = rows.sparkSession
    held: tuple = (Numbered({}), {}, [])
    if block is not None:
        counts = {(r["k"], r["shingle"]): r["n"] for r in corpus_counts(rows, block.words, block.vocabulary()).toLocalIterator()}  # the block's shingles at most
        held = (block.words, block.prefixes(counts), block.ids)
    shared = spark.sparkContext.broadcast(held)

    def match(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known, prefixes, ids = shared.value
        for frame in frames:
            n, spans, items = [], [], []
            for text in frame["text"]:
                words = words_of(text)
                got, of = matches(words, known, prefixes) if prefixes else ([], ())
                n.append(len(words))
                spans.append([{"s": s, "e": e} for s, e in got])
                items.append([ids[i] for i in of])
            yield pd.DataFrame({"key": frame["key"], "n_words": n, "spans": spans, "items": items})

    return rows.mapInPandas(match, "key string, n_words long, spans array<struct<s:long,e:long>>, items array<string>")


def united(spans: pd.Series) -> pd.Series:
    """The number of words in the union of each row's spans."""

    def length(row) -> int:
        total = last = 0
        for s, e in sorted((x["s"], x["e"]) for x in row):
            total += max(0, e - max(s, last))
            last = max(last, e)
        return total

    return spans.map(length).astype("int64")


def decontaminate(docs: DataFrame, benchmark: DataFrame, size: int = 10, block_windows: int = 200_000) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated, spans, items: a row per row of ``docs``."""
    rows = docs.select(id_as_string(docs, "doc_id"), "text")
    blocks = blocks_of(benchmark, size, block_windows)
    block, more = next(blocks, None), next(blocks, None)
    if more is None:
        found = find_matches(rows.withColumnRenamed("doc_id", "key"), block).withColumnRenamed("key", "doc_id")
    else:  # a row is known by its place in a written table: rows that repeat stay apart
        keyed = written(rows.withColumn("key", F.monotonically_increasing_id().cast("string")), "keyed")
        parts = []
        while block is not None:
            parts.append(written(find_matches(keyed.select("key", "text"), block), "matches"))
            block, more = more, next(blocks, None) if more is not None else None
        found = parts[0]
        for part in parts[1:]:
            found = found.unionByName(part)
        found = found.groupBy("key").agg(
            F.max("n_words").alias("n_words"), F.flatten(F.collect_list("spans")).alias("spans"), F.flatten(F.collect_list("items")).alias("items")
        )
        found = keyed.select("key", "doc_id").join(found, "key").drop("key")
    n_hit = F.pandas_udf(united, "long")
    found = found.withColumn("items", F.array_sort(F.array_distinct("items")))
    sha = F.sha2(F.array_join("items", ","), 256)
    return found.select(
        id_back(docs, "doc_id"), "n_words", n_hit("spans").alias("n_hit"), F.size("items").cast("long").alias("n_items"), sha.alias("items_sha256"), (F.size("spans") > 0).alias("contaminated"), "spans", "items"
    )
