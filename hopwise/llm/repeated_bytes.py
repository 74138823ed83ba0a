"""Removal of byte strings of a given length that occur more than once in the corpus, by prefix-free parsing.

A rolling hash places triggers that depend on content alone. They cut every text into phrases; distinct phrases are
the dictionary, and the order of the dictionary's suffixes tells which strings are equal:

1. Each string of ``length`` bytes has one trigger: of the grams that start in its first ``span`` bytes, the last of
   those with the least rolling hash. Neighbouring strings with one trigger form a run; the bytes under all strings
   of a run are its phrase. Neighbouring phrases overlap by ``length - 1`` bytes, so each string lies inside one
   phrase: to the depth of ``length`` the order of the dictionary's suffixes is the order of the corpus, and the
   parse adds no more than how often each phrase occurs. (A suffix array of the parse would order beyond that depth,
   which nothing here asks for.)
2. Equal strings have their trigger at the same place, and the same bytes behind it, at least ``length - span + 1``:
   these bytes' hash is the run's group, and deals the dictionary to tasks. Only groups met twice can hold a repeat.
   Equal phrases are one entry of the dictionary with a count; an entry with a count of two or more is repeated as a
   whole.
3. The entries of groups with several are gathered some megabytes at a time, whole groups together, and their
   suffixes ranked by multiplying prefixes, to the depth of ``length``: strings of equal rank are equal byte for byte.
   A group above ``most_entries`` (a passage in a great many contexts) is no task's load: its strings are known by
   128-bit hashes instead, and counted across the corpus.
4. The spans found are united for each document and cut out of its bytes.

Beside the bytes, ``n_shared_windows`` counts the windows of ``passage_words`` words (between white space) of a
document that another document holds too, by the same triggers over words: a passage of 50 words may have fewer than
``length`` bytes, and is then reported but not cut.

Null text is empty. A text shorter than ``length`` loses nothing. Rows that repeat an id and its text are copies like
any others: all lose the bytes. Matches never cross documents; overlapping occurrences inside one count. An empty
table gives an empty table; other columns are ignored. Rows are known by their place in a written table, phrases and
strings across tasks by 128 bits.

No group of rows is collected unless it is known to be small; joins on groups deal the rows of hot ones over tasks.
Shuffled are the runs (about one per ``span / 2`` bytes), the phrases of mixed groups, and each text twice.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, forget, hot_join, id_as_string, id_back, mixed, text_key, written

GRAM = 16
CHUNK = 1 << 18
#: bytes of phrases that one call ranks
RANKED = 1 << 18
WORDS = re.compile(r"[^\x20\x09-\x0D]+")
_LOW = np.uint64((1 << 20) - 1)


class RollingHash:
    """Polynomial hashes modulo 2^64 of random values per byte or word: any stretch of a text by one subtraction."""

    BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)  # odd, 5 modulo 8: long cycles

    def __init__(self, most: int, kind: int = 0):
        base = self.BASES[kind]
        self.salt = np.uint64(base >> 1)
        self.powers = self._powers(base, most)
        self.inverses = self._powers(pow(base, -1, 2**64), most)
        self.values = mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F) + self.salt)

    @staticmethod
    def _powers(base: int, n: int) -> np.ndarray:
        out = np.full(n, base, np.uint64)
        out[0] = 1
        return np.multiply.accumulate(out)

    def sums(self, data: np.ndarray) -> np.ndarray:
        """``data`` holds bytes, or 64-bit hashes of words."""
        values = self.values[data] if data.dtype == np.uint8 else mixed(data ^ self.salt)
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(values * self.powers[: len(data)], out=out[1:])
        return out

    def of(self, sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mixed((sums[end] - sums[start]) * self.inverses[start] + (end - start).astype(np.uint64))


def rolling_hashes(length: int) -> tuple[RollingHash, RollingHash]:
    """Two independent hashes, kept by the worker: together 128 bits."""
    import sys

    kept = sys.__dict__.setdefault("_rolling_hashes", {})
    if length not in kept:
        most = CHUNK + 2 * length + 64
        kept[length] = (RollingHash(most, 0), RollingHash(most, 1))
    return kept[length]


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` neighbours, by doubling."""
    have, out = 1, x
    while 2 * have <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


RUN = ("r", "c", "c2", "doc", "lo", "hi", "at")


def runs_of(data: np.ndarray, sizes: list[int], rolling: tuple[RollingHash, RollingHash], length: int, span: int, gram: int) -> dict[str, np.ndarray]:
    """Runs of texts that lie one after another in ``data``, each of ``sizes`` units.

    r (group), c and c2 (phrase), doc (number of the text), lo, hi (first and last start of the run's strings) and at
    (its trigger), the three counted from the text's own start.
    """
    begins = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)
    out: dict[str, list] = {k: [] for k in RUN}
    n = len(data) - length + 1
    for first in range(0, max(n, 0), CHUNK):
        last = min(first + CHUNK, n)  # starts of strings in this chunk
        part, m = data[first : last + length - 1], last - first
        sums, sums2 = rolling[0].sums(part), rolling[1].sums(part)
        starts = np.arange(m + span - 1)
        grams = rolling[0].of(sums, starts, starts + gram)
        # the place, upside down, in the low bits: of equal hashes the last wins
        least = sliding_least((grams & ~_LOW) | (_LOW - starts.astype(np.uint64)), span)
        at = (_LOW - (least & _LOW)).astype(np.int64)
        d0, d1 = np.searchsorted(begins, [first, last - 1], side="right") - 1
        own = np.arange(d0, d1 + 1)
        doc = np.repeat(own, np.minimum(begins[own + 1], last) - np.maximum(begins[own], first))
        inside = np.flatnonzero(np.arange(first, last) + length <= begins[doc + 1])  # strings that end in their text
        if not len(inside):
            continue
        at, doc = at[inside], doc[inside]
        cut = np.flatnonzero((np.diff(at) != 0) | (np.diff(doc) != 0)) + 1
        lo = inside[np.concatenate([[0], cut])]
        hi = inside[np.concatenate([cut - 1, [len(inside) - 1]])]
        heads = np.concatenate([[0], cut])
        at, doc = at[heads], doc[heads]
        out["r"].append(rolling[0].of(sums, at, at + (length - span + 1)))
        place = (at - lo).astype(np.uint64) * np.uint64(0x9FB21C651E98DF25)
        out["c"].append(mixed(rolling[0].of(sums, lo, hi + length) + place))
        out["c2"].append(mixed(rolling[1].of(sums2, lo, hi + length) + place))
        out["doc"].append(doc)
        for name, x in (("lo", lo), ("hi", hi), ("at", at)):
            out[name].append(x + first - begins[doc])
    return {k: np.concatenate(v) if v else np.zeros(0, np.uint64 if k in ("r", "c", "c2") else np.int64) for k, v in out.items()}


def windows_of(data: np.ndarray, sizes: list[int], rolling: tuple[RollingHash, RollingHash], length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Two hashes, text number and start of every string of ``length`` units inside one of the texts in ``data``."""
    begins = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)
    out: list[tuple] = []
    n = len(data) - length + 1
    for first in range(0, max(n, 0), CHUNK):
        last = min(first + CHUNK, n)
        part = data[first : last + length - 1]
        doc = np.searchsorted(begins, np.arange(first, last), side="right") - 1
        inside = np.flatnonzero(np.arange(first, last) + length <= begins[doc + 1])
        doc = doc[inside]
        h = [x.of(x.sums(part), inside, inside + length).view(np.int64) for x in rolling]
        out.append((*h, doc, inside + first - begins[doc]))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 4


def gathered(items: Iterator, size, most: int) -> Iterator[list]:
    """Lists of neighbouring items of about ``most`` units in all."""
    held, total = [], 0
    for x in items:
        held.append(x)
        total += size(x)
        if total >= most:
            yield held
            held, total = [], 0
    if held:
        yield held


def encoded(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


def byte_runs(texts: DataFrame, length: int, span: int) -> DataFrame:
    """r, c, c2, rid, lo, hi, at: the runs of ``texts(rid, text)``."""

    def find(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rolling = rolling_hashes(length)
        for frame in frames:
            pairs = ((rid, encoded(text)) for rid, text in zip(frame["rid"], frame["text"], strict=True) if 4 * len(text) >= length)
            for some in gathered(((rid, data) for rid, data in pairs if len(data) >= length), lambda x: len(x[1]), CHUNK):
                rids = np.array([rid for rid, _ in some], np.int64)
                runs = runs_of(np.frombuffer(b"".join(x for _, x in some), np.uint8), [len(x) for _, x in some], rolling, length, span, GRAM)
                keys = {k: runs[k].view(np.int64) for k in ("r", "c", "c2")}
                yield pd.DataFrame(keys | {"rid": rids[runs["doc"]]} | {k: runs[k].astype(np.int32) for k in ("lo", "hi", "at")})

    return texts.mapInPandas(find, "r long, c long, c2 long, rid long, lo int, hi int, at int")


def string_ranks(data: np.ndarray, length: int) -> np.ndarray:
    """For every place, a number that is equal where the ``length`` bytes from there are equal, and grows with their order.

    Ranks of a depth, taken two or three at a time, give the ranks of twice or three times the depth; the last overlap.
    """
    if len(data) < length:
        return np.zeros(0, np.int64)
    have = min(7, length)
    key = np.zeros(len(data) - have + 1, np.int64)
    for k in range(have):
        key = (key << 8) | data[k : k + len(key)]
    while have < length:
        rank = np.unique(key, return_inverse=True)[1]
        most = int(rank.max()) + 1
        if most**3 < 2**63:  # three ranks at once
            step = min(have, -(-(length - have) // 2))
            last = min(2 * step, length - have)
        else:
            step = last = min(have, length - have)
        n = len(rank) - last
        key = rank[:n] * most + rank[step : step + n]
        if last > step:
            key = key * most + rank[last:]
        have += last
    return np.unique(key, return_inverse=True)[1]


def repeated_starts(phrases: list[bytes], counts: list[int], length: int) -> list[np.ndarray]:
    """For each phrase that occurs once, the places in it of strings that another phrase, or another place in it, holds too."""
    sizes = np.array([len(x) for x in phrases])
    rank = string_ranks(np.frombuffer(b"".join(phrases), np.uint8), length)
    begins = np.cumsum(sizes) - sizes
    inside = np.concatenate([np.arange(b, b + n - length + 1) for b, n in zip(begins.tolist(), sizes.tolist(), strict=True)])
    owner = np.repeat(np.arange(len(phrases)), sizes - length + 1)
    rank = rank[inside]
    seen = np.bincount(rank, np.minimum(counts, 2)[owner])
    hit = (seen[rank] > 1) & (np.array(counts)[owner] == 1)
    cuts = np.searchsorted(owner[hit], np.arange(len(phrases) + 1))
    places = (inside - begins[owner])[hit]
    return [places[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]


def stretches(starts: np.ndarray, length: int) -> list[tuple[int, int]]:
    """[start, end) of the bytes under strings at sorted ``starts``; neighbouring starts make one."""
    if not len(starts):
        return []
    cut = np.flatnonzero(np.diff(starts) > 1) + 1
    first, last = starts[np.concatenate([[0], cut])], starts[np.concatenate([cut - 1, [len(starts) - 1]])]
    return list(zip(first.tolist(), (last + length).tolist(), strict=True))


def ranked_spans(entries: DataFrame, length: int) -> DataFrame:
    """rid, s, e: removed stretches from ``entries(r, rid, lo, n, phrase)``, groups of a bounded number of rows."""

    def groups(frames: Iterator[pd.DataFrame]) -> Iterator[list]:
        group: list = []
        for frame in frames:
            for row in frame.itertuples(index=False):
                if group and row.r != group[0].r:
                    yield group
                    group = []
                group.append(row)
        if group:
            yield group

    def compare(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        wanted = (g for g in groups(frames) if len(g) > 1 and any(x.n == 1 for x in g))
        for some in gathered(wanted, lambda g: sum(len(x.phrase) for x in g), RANKED):
            rows = [x for g in some for x in g]
            found = repeated_starts([x.phrase for x in rows], [x.n for x in rows], length)
            out = [(x.rid, x.lo + s, x.lo + e) for x, starts in zip(rows, found, strict=True) for s, e in stretches(starts, length)]
            if out:
                yield pd.DataFrame(out, columns=["rid", "s", "e"])

    dealt = entries.select("r", "rid", "lo", "n", "phrase").repartition("r").sortWithinPartitions("r", "rid", "lo")
    return dealt.mapInPandas(compare, "rid long, s int, e int")


def counted_spans(entries: DataFrame, length: int) -> DataFrame:
    """As ``ranked_spans``, for groups of any size: the strings' 128-bit hashes are counted across the corpus."""

    def strings(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rolling = rolling_hashes(length)
        for frame in frames:
            for some in gathered(frame.itertuples(index=False), lambda x: len(x.phrase), CHUNK):
                h, h2, doc, at = windows_of(np.frombuffer(b"".join(x.phrase for x in some), np.uint8), [len(x.phrase) for x in some], rolling, length)
                rid, lo, n = (np.array([getattr(x, k) for x in some]) for k in ("rid", "lo", "n"))
                yield pd.DataFrame({"h": h, "h2": h2, "n": n[doc].astype(np.int32), "rid": rid[doc], "s": (at + lo[doc]).astype(np.int32)})

    rows = written(entries.select("rid", "lo", "n", "phrase").mapInPandas(strings, "h long, h2 long, n int, rid long, s int"), "strings")
    sizes = rows.groupBy("h", "h2").agg(F.sum("n").alias("all"), F.count_if(F.col("n") == 1).alias("size")).where("all > 1 and size > 0")
    found = hot_join(rows.where("n = 1"), sizes.select("h", "h2", "size"), ["h", "h2"], "size", ["rid", "s"])
    return found.select("rid", "s", (F.col("s") + length).alias("e"))


def removed_spans(texts: DataFrame, length: int, span: int, most_entries: int) -> DataFrame:
    """rid, spans (array of start, end; they may overlap) for the rows of ``texts(rid, text)``, a written table, that lose bytes."""
    runs = written(byte_runs(texts, length, span), "runs")
    groups = runs.groupBy("r").agg(F.count("*").alias("size")).where("size > 1")
    held = written(hot_join(runs, groups, ["r"], "size", ["rid", "lo"]).drop("size"), "held")
    forget(runs)
    counted = held.groupBy("r", "c", "c2").agg(F.count("*").alias("size"), F.min(F.struct("rid", "lo", "hi", "at")).alias("x"))
    entries = written(counted.select("r", "c", "c2", "size", F.least("size", F.lit(2)).cast("int").alias("n"), "x.*"), "entries")
    twice = entries.where("n > 1").select("r", "c", "c2", "size")
    whole = hot_join(held, twice, ["r", "c", "c2"], "size", ["rid", "lo"]).select("rid", F.col("lo").alias("s"), (F.col("hi") + length).cast("int").alias("e"))
    sizes = entries.groupBy("r").agg(F.count("*").alias("m"), F.min("n").alias("fewest")).where("m > 1 and fewest = 1").select("r", "m")
    mixed_ = hot_join(entries, sizes, ["r"], "m", ["c"])
    wanted = mixed_.groupBy("rid").agg(F.collect_list(F.struct("r", "lo", "hi", "n", "m")).alias("wanted"))  # a text's phrases at most

    def phrases(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for rid, text, wanted in zip(frame["rid"], frame["text"], frame["wanted"], strict=True):
                data = encoded(text)
                out += [(w["r"], rid, w["lo"], w["n"], w["m"], data[w["lo"] : w["hi"] + length]) for w in wanted]
            yield pd.DataFrame(out, columns=["r", "rid", "lo", "n", "m", "phrase"])

    phrased = written(texts.join(wanted, "rid").mapInPandas(phrases, "r long, rid long, lo int, n int, m long, phrase binary"), "phrases")
    few = ranked_spans(phrased.where(F.col("m") <= most_entries), length)
    many = counted_spans(phrased.where(F.col("m") > most_entries), length)
    spans = written(whole.unionByName(few).unionByName(many), "spans")
    for used in (held, entries, phrased):
        forget(used)
    return spans.groupBy("rid").agg(F.collect_set(F.struct("s", "e")).alias("spans"))


def shared_windows(texts: DataFrame, words: int) -> DataFrame:
    """rid, n_shared_windows: how many of a text's windows of ``words`` words other rows of ``texts(rid, text)`` hold too.

    Equal texts are one before anything is joined. Of the others, only the runs of windows whose group two texts
    have are hashed window by window.
    """
    span = max(1, words * 3 // 4)
    gram = min(4, words - span + 1)
    keys = written(texts.select("rid", text_key("text").alias("k")), "text-keys")
    copies = written(keys.groupBy("k").agg(F.min("rid").alias("first"), F.count("*").alias("copies")), "copies")
    again = hot_join(keys, copies.where("copies > 1"), ["k"], "copies", ["rid"])
    repeats = written(again.where("rid <> first").select("rid"), "repeats")
    distinct = texts.join(repeats, "rid", "left_anti")

    def hashed(frames: Iterator[pd.DataFrame]) -> Iterator[tuple[pd.DataFrame, list[int], list[np.ndarray]]]:
        known = WordHashes(200_000)
        for frame in frames:
            rows = ((i, known.of(WORDS.findall(t))) for i, t in enumerate(frame["text"]) if len(t) >= 2 * words - 1)
            for some in gathered(((i, h) for i, h in rows if len(h) >= words), lambda x: len(x[1]), CHUNK // 4):
                yield frame, [i for i, _ in some], [h for _, h in some]

    def groups_of(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rolling = rolling_hashes(words)
        for frame, at, hashes in hashed(frames):
            runs = runs_of(np.concatenate(hashes), [len(h) for h in hashes], rolling, words, span, gram)
            rid = frame["rid"].to_numpy()[np.array(at)][runs["doc"]]
            yield pd.DataFrame({"r": runs["r"].view(np.int64), "rid": rid}).drop_duplicates()

    def windows(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rolling = rolling_hashes(words)
        for frame, at, hashes in hashed(frames):
            data, sizes = np.concatenate(hashes), [len(h) for h in hashes]
            runs = runs_of(data, sizes, rolling, words, span, gram)
            good = [np.isin(runs["r"][runs["doc"] == k].view(np.int64), frame["groups"].iloc[i]) for k, i in enumerate(at)]
            keep = np.concatenate(good) if good else np.zeros(0, bool)
            begins = np.cumsum(sizes) - np.array(sizes)
            marks = np.zeros(len(data) + 1, np.int64)
            base = begins[runs["doc"][keep]]
            np.add.at(marks, runs["lo"][keep] + base, 1)
            np.add.at(marks, runs["hi"][keep] + base + 1, -1)
            h, h2, doc, s = windows_of(data, sizes, rolling, words)
            wanted = np.cumsum(marks)[s + begins[doc]] > 0
            rid = frame["rid"].to_numpy()[np.array(at)][doc[wanted]]
            yield pd.DataFrame({"h": h[wanted], "h2": h2[wanted], "rid": rid})

    first = written(distinct.select("rid", "text").mapInPandas(groups_of, "r long, rid long"), "word-groups")
    groups = first.groupBy("r").agg(F.count("*").alias("size"), F.min("rid").alias("low"), F.max("rid").alias("high")).where("low < high").select("r", "size")
    wanted = hot_join(first, groups, ["r"], "size", ["rid"]).groupBy("rid").agg(F.collect_set("r").alias("groups"))
    rows = written(distinct.select("rid", "text").join(wanted, "rid").mapInPandas(windows, "h long, h2 long, rid long"), "word-windows")
    forget(first)
    shared = rows.groupBy("h", "h2").agg(F.count("*").alias("size"), F.min("rid").alias("low"), F.max("rid").alias("high")).where("low < high").select("h", "h2", "size")
    found = hot_join(rows, shared, ["h", "h2"], "size", ["rid"]).groupBy(F.col("rid").alias("first")).agg(F.count("*").alias("n"))
    n_words = F.regexp_count("text", F.lit(WORDS.pattern))
    many = written(copies.where("copies > 1").select(F.col("first").alias("rid"), "copies"), "many")
    whole = texts.join(many, "rid").select(F.col("rid").alias("first"), F.greatest(F.lit(0), n_words - (words - 1)).cast("long").alias("all"))
    per_text = copies.join(found, "first", "left").join(whole, "first", "left").select("k", "copies", F.coalesce("all", "n", F.lit(0)).cast("long").alias("n_shared_windows"))
    return hot_join(keys, per_text, ["k"], "copies", ["rid"]).select("rid", "n_shared_windows")


def remove_repeats(
    docs: DataFrame, length: int = 400, span: int = 300, most_entries: int = 2048, passage_words: int | None = None, keep_bytes: bool = False
) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, and the remaining bytes as ``kept`` if asked for: a row per row of ``docs``.

    With ``passage_words`` there is n_shared_windows too.
    """
    if not GRAM <= length - span + 1:
        raise ValueError("length must exceed span by a gram")
    rows = docs.select(id_as_string(docs, "doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    texts = written(rows.withColumn("rid", F.monotonically_increasing_id()), "texts")
    spans = removed_spans(texts.select("rid", "text"), length, span, most_entries)
    counts = shared_windows(texts.select("rid", "text"), passage_words) if passage_words else None
    more = ["n_shared_windows"] if passage_words else []

    def cut(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for text, spans in zip(frame["text"], frame["spans"], strict=True):
                data = encoded(text)
                kept, last, n = [], 0, 0
                for s, e in merged([] if spans is None else spans):
                    kept.append(data[last:s])
                    last, n = e, n + 1
                rest = b"".join([*kept, data[last:]])
                out.append((len(data), len(data) - len(rest), n, hashlib.sha256(rest).hexdigest(), *[rest] * keep_bytes))
            made = pd.DataFrame(out, columns=["n_bytes", "n_removed", "n_spans", "kept_sha256", *["kept"] * keep_bytes])
            for name in ["doc_id", *more]:
                made[name] = frame[name].to_numpy()
            yield made

    joined = texts.join(spans, "rid", "left")
    if counts is not None:
        joined = joined.join(counts, "rid")
    schema = f"n_bytes long, n_removed long, n_spans long, kept_sha256 string{', kept binary' * keep_bytes}, doc_id string{', n_shared_windows long' * len(more)}"
    found = joined.select("doc_id", "text", "spans", *more).mapInPandas(cut, schema)
    return found.select(id_back(docs, "doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256", *["kept"] * keep_bytes, *more)


def merged(spans) -> list[tuple[int, int]]:
    """Maximal stretches of the union; stretches that touch are one."""
    out: list[list[int]] = []
    for s, e in sorted((x["s"], x["e"]) for x in spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(e, out[-1][1])
        else:
            out.append([s, e])
    return [tuple(x) for x in out]
