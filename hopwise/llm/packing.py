"""Best-fit packing of token sequences by bin completion.

Documents become ids and an end id; only a longer one than a sequence is cut, into full pieces from its end, so
that one shorter piece at most is left, the first. What matters for packing is how many pieces there are of each
length: at most ``capacity`` numbers, whatever the size of the corpus. On these the driver searches: best-fit
decreasing, done on whole groups of equal bins, gives the first incumbent; if it misses the lower bound, a
branch-and-bound completes bins around the largest length left, trying fillings that no other filling dominates
(those that waste least first), in as many bins at once as the counts allow or half as many, and so on down to one,
and gives up a branch when its waste exceeds what a better solution may waste. All such fillings are enumerated: the
search is exact if it ends. ``steps`` is its budget (None: no limit); at its end the incumbent stands, and the
``Solution`` tells the lower bound beside it and whether the search was complete. Every piece is placed whatever the
search does.

Pieces are numbered within their length (a number within the task that made them, plus a prefix sum over tasks),
and the number alone says which bin of which pattern a piece goes to: no group of equal lengths is ever gathered.

Null text is empty and gives one piece, the end id. Rows that repeat are pieces of their own. An empty table gives
an empty table; other columns are ignored.
"""

from __future__ import annotations

import logging
import zlib
from bisect import bisect_right
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import id_as_string, id_back, written
from .tokens import tokenizer

log = logging.getLogger(__name__)

#: budget of the search, some two seconds
STEPS = 100_000

#: (number of bins, ((length, how many of it in each bin), ...))
Pattern = tuple[int, tuple[tuple[int, int], ...]]


def lower_bound(counts: dict[int, int], capacity: int) -> int:
    """The greatest of the bounds by halves: for each k, lengths over capacity - k alone, over half alone, and room for the rest down to k."""
    total = -(-sum(s * n for s, n in counts.items()) // capacity)
    best = total
    for k in sorted({s for s in counts if 2 * s <= capacity} | {1}):
        big = sum(n for s, n in counts.items() if s > capacity - k)
        half = [(s, n) for s, n in counts.items() if capacity - k >= s > capacity / 2]
        small = sum(s * n for s, n in counts.items() if capacity / 2 >= s >= k)
        alone = sum(n for _, n in half)
        room = alone * capacity - sum(s * n for s, n in half)
        best = max(best, big + alone + max(0, -(-(small - room) // capacity)))
    return best


def best_fit(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """Best-fit decreasing over groups of equal bins."""
    rooms: dict[int, list[list]] = defaultdict(list)  # room left -> [bins, content]
    open_rooms: list[int] = []  # sorted
    for size in sorted(counts, reverse=True):
        left = counts[size]
        while left:
            at = bisect_right(open_rooms, size - 1)
            room = open_rooms[at] if at < len(open_rooms) else capacity
            if at < len(open_rooms):
                bins, content = rooms[room].pop()
                if not rooms[room]:
                    open_rooms.pop(at)
                    del rooms[room]
            else:
                bins, content = -(-left // (capacity // size)), ()
            each = min(room // size, left)
            full = min(bins, left // each)
            rest = bins - full
            put = [(full, each)] + ([(rest, 0)] if rest and at < len(open_rooms) or rest and content else [])
            left -= full * each
            if rest and not content and room == capacity:  # a last new bin that is not filled up
                put = [(full, each)] + ([(1, left)] if left else [])
                left = 0
            for n, k in put:
                if n:
                    now = room - k * size
                    if now not in rooms:
                        open_rooms.insert(bisect_right(open_rooms, now), now)
                    rooms[now].append([n, content + (((size, k),) if k else ())])
    return [(n, content) for groups in rooms.values() for n, content in groups]


def bins_of(patterns: list[Pattern]) -> int:
    return sum(n for n, _ in patterns)


class Budget:
    """Steps that a search may still take; None is no limit."""

    def __init__(self, steps: int | None):
        self.left, self.spent_all = steps, False

    def step(self) -> bool:
        if self.left is None:
            return True
        self.left -= 1
        self.spent_all = self.spent_all or self.left < 0
        return self.left >= 0


def fillings(room: int, counts: dict[int, int], most_waste: int, budget: Budget, all_kinds: bool = False) -> Iterator[tuple[tuple[int, int], ...]]:
    """All undominated fillings of ``room`` from ``counts``, least waste first; with ``all_kinds`` dominated ones too.

    Bits of an integer tell which sums can be reached with the sizes up to each; walking back from the largest
    size, largest numbers first, reads fillings off them, and each path of the walk ends in a filling.
    """
    sizes = sorted(s for s, n in counts.items() if n and s <= room)
    mask, reach = (1 << (room + 1)) - 1, [1]
    for size in sizes:
        bits, left, take = reach[-1], min(counts[size], room // size), 1
        while left:
            step = min(take, left)
            bits |= (bits << (step * size)) & mask
            left, take = left - step, take * 2
        reach.append(bits)
    sums = reach[-1]
    while sums:
        target = sums.bit_length() - 1
        if room - target > most_waste:
            return
        sums ^= 1 << target
        stack: list[tuple[int, int, tuple[tuple[int, int], ...]]] = [(len(sizes), target, ())]
        while stack:
            if not budget.step():
                return
            i, rest, chosen = stack.pop()
            if not rest:
                if all_kinds or not _dominated(chosen, counts, room - target):
                    yield chosen
                continue
            i = min(i, bisect_right(sizes, rest))
            if not i:
                continue
            size = sizes[i - 1]
            for k in range(min(counts[size], rest // size) + 1):
                if reach[i - 1] >> (rest - k * size) & 1:
                    stack.append((i - 1, rest - k * size, (*chosen, (size, k)) if k else chosen))


def _dominated(chosen: tuple[tuple[int, int], ...], counts: dict[int, int], waste: int) -> bool:
    """Another item would fit too, or two items could be one that is at hand: the other filling leaves the easier rest."""
    use = dict(chosen)
    if waste and any(counts.get(w, 0) > use.get(w, 0) for w in range(1, waste + 1)):
        return True
    for i, (a, k) in enumerate(chosen):
        if k > 1 and counts.get(2 * a, 0) > use.get(2 * a, 0):
            return True
        if any(counts.get(a + b, 0) > use.get(a + b, 0) for b, _ in chosen[i + 1 :]):
            return True
    return False


def least_waste(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """Around the largest length left, always the filling that wastes least, in as many bins as the counts allow."""
    left, out = dict(counts), []
    for largest in sorted(counts, reverse=True):
        while left[largest]:
            left[largest] -= 1
            use = dict(next(fillings(capacity - largest, left, capacity, Budget(None), True), ()))
            left[largest] += 1
            use[largest] = use.get(largest, 0) + 1
            n = min(left[s] // k for s, k in use.items())
            for s, k in use.items():
                left[s] -= n * k
            out.append((n, tuple(use.items())))
    return out


@dataclass
class Solution:
    patterns: list[Pattern]
    bins: int
    bound: int  # no packing has fewer bins
    proven: bool  # the bins are as few as can be


def solve(counts: dict[int, int], capacity: int, steps: int | None = STEPS) -> list[Pattern]:
    """The patterns that ``search`` finds."""
    return search(counts, capacity, steps).patterns


def search(counts: dict[int, int], capacity: int, steps: int | None = STEPS) -> Solution:
    """Patterns that hold all of ``counts`` (length -> pieces), in as few bins as the search finds in ``steps``."""
    counts = {s: n for s, n in counts.items() if n}
    if not counts:
        return Solution([], 0, 0, True)
    best, bound, total = best_fit(counts, capacity), lower_bound(counts, capacity), sum(s * n for s, n in counts.items())
    if bins_of(best) > bound:
        best = min(best, least_waste(counts, capacity), key=bins_of)
    fewest, budget = bins_of(best), Budget(steps)
    sizes = sorted(counts, reverse=True)

    def choices(left: dict[int, int], waste: int) -> Iterator[tuple[int, tuple[tuple[int, int], ...], int]]:
        """(bins, content, waste) around the largest length left, what wastes least in the most bins first."""
        largest = next(s for s in sizes if left[s])
        rest = left | {largest: left[largest] - 1}
        for option in fillings(capacity - largest, rest, (fewest - 1) * capacity - total - waste, budget):
            use = dict(option)
            use[largest] = use.get(largest, 0) + 1
            lost = capacity - sum(s * k for s, k in use.items())
            n = min(left[s] // k for s, k in use.items())
            while n:
                if waste + n * lost <= (fewest - 1) * capacity - total:
                    yield n, tuple(use.items()), n * lost
                n //= 2

    made: list[Pattern] = []
    left, waste = dict(counts), 0
    stack = [(choices(left, 0), 0)]
    while stack and fewest > bound and budget.step():
        options, before = stack[-1]
        choice = next(options, None)
        if choice is None:
            stack.pop()
            if made:  # undo the choice that led here
                n, content = made.pop()
                for s, k in content:
                    left[s] += n * k
            continue
        n, content, lost = choice
        for s, k in content:
            left[s] -= n * k
        made.append((n, content))
        waste = before + lost
        if any(left.values()):
            stack.append((choices(dict(left), waste), waste))
            continue
        best, fewest = list(made), bins_of(made)
        n, content = made.pop()
        for s, k in content:
            left[s] += n * k
    return Solution(best, fewest, bound, fewest == bound or not budget.spent_all)


def make_pieces(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2, keep_ids: bool = True) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, task, number (of the piece among the task's of its length), and ids."""
    end = np.array([end_id], "<u4").tobytes()

    def cut(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tokens, task = tokenizer(path), TaskContext.get().partitionId()
        numbers = [0] * (capacity + 1)
        for frame in frames:
            rows = []
            for doc_id, text in zip(frame["doc_id"], frame["text"], strict=True):
                ids = tokens.ids(text) + end
                n = len(ids) // 4
                first = n % capacity or capacity
                for piece, stop in enumerate(range(first, n + 1, capacity)):
                    start = 0 if not piece else stop - capacity
                    own = ids[4 * start : 4 * stop]
                    length = stop - start
                    rows.append((doc_id, piece, start, length, zlib.crc32(own), task, numbers[length], *[own] * keep_ids))
                    numbers[length] += 1
            yield pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32", "task", "number", *["ids"] * keep_ids])

    schema = f"doc_id string, piece int, start long, length long, ids_crc32 long, task int, number long{', ids binary' * keep_ids}"
    made = docs.select(id_as_string(docs, "doc_id"), "text").mapInPandas(cut, schema)
    return made.withColumn("doc_id", id_back(docs, "doc_id"))


class Places:
    """Where the pieces of each length go: ranges of numbers, each to a run of equal bins."""

    def __init__(self, table: dict[int, np.ndarray]):
        self.table = table  # length -> rows: first number, of it in each bin, first bin, offset

    @classmethod
    def of_patterns(cls, patterns: list[Pattern]) -> Places:
        ranges: dict[int, list[tuple[int, int, int, int]]] = defaultdict(list)
        used: dict[int, int] = defaultdict(int)
        bin_ = 0
        for n, content in patterns:
            offset = 0
            for size, k in content:
                ranges[size].append((used[size], k, bin_, offset))
                used[size] += n * k
                offset += size * k
            bin_ += n
        return cls({s: np.array(x, dtype=np.int64).T for s, x in ranges.items()})

    def of(self, length: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
        for size in np.unique(length):
            mine = length == size
            first, k, bin_, at = self.table[int(size)]
            r = np.searchsorted(first, number[mine], side="right") - 1
            within = number[mine] - first[r]
            sequence[mine] = bin_[r] + within // k[r]
            offset[mine] = at[r] + within % k[r] * size
        return sequence, offset


def place_pieces(pieces: DataFrame, capacity: int = 1024, steps: int | None = STEPS) -> DataFrame:
    """``pieces(length, task, number, ...)``, a table that stays as it is, with sequence_id and offset in place of task and number."""
    spark = pieces.sparkSession
    groups = pieces.groupBy("length", "task").agg(F.count("*").alias("n"))
    totals = {r["length"]: r["n"] for r in groups.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # capacity rows at most
    found = search(totals, capacity, steps)
    if not found.proven:
        log.info("packed into %d sequences; no packing has fewer than %d", found.bins, found.bound)
    places = spark.sparkContext.broadcast(Places.of_patterns(found.patterns).table)  # some patterns per length
    before = F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1))
    based = groups.withColumn("base", F.coalesce(before, F.lit(0))).drop("n")
    numbered = pieces.join(based, ["length", "task"]).withColumn("number", F.col("number") + F.col("base")).drop("base", "task")

    @F.pandas_udf("sequence_id long, offset long")
    def place(length: pd.Series, number: pd.Series) -> pd.DataFrame:
        sequence, offset = Places(places.value).of(length.to_numpy(), number.to_numpy())
        return pd.DataFrame({"sequence_id": sequence, "offset": offset})

    return numbered.withColumn("_at", place("length", "number")).select("*", "_at.sequence_id", "_at.offset").drop("_at", "number")


def pack_documents(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2, keep_ids: bool = True, steps: int | None = STEPS) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset, and the piece's ids (little-endian unsigned 32-bit)."""
    pieces = written(make_pieces(docs, path, capacity, end_id, keep_ids), "pieces")
    out = place_pieces(pieces, capacity, steps)
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", *["ids"] * keep_ids)
