"""Token ids in a compact file format: canonical length-limited Huffman codes over the counts of the whole corpus.

The format is a folder with two Parquet tables. ``codebook`` has (id, length): the code lengths, from which codes
follow (canonical: by length, then id, counting up). ``blocks`` has one row per block: part and block (their order
is the order of documents by doc_id), the documents in it (doc_ids, lengths), n_ids, ``checkpoints`` (the bit offset
of every ``every``-th id) and ``payload`` (the bits, most significant first, padded to bytes). A block needs nothing
but the codebook, and decoding starts at any checkpoint; the decoder runs all stretches between checkpoints side
by side through one table that maps the next ``limit`` bits to an id and its code length.

Lengths come from package-merge, so no code is longer than ``limit`` bits. Counts are summed before the shuffle;
the driver holds one count per id of the vocabulary. Documents are range-partitioned by doc_id (null first; ties
keep together, in the order of their ids), and blocks hold whole documents: about ``block_ids`` ids, or one longer
document. Null text is empty; every document has its end id. An empty table gives an empty codebook and no blocks.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import forget, id_as_string, id_back, shared_folder, written
from .tokens import tokenizer

LIMIT, EVERY, BLOCK_IDS = 18, 128, 65_536
#: blocks that a task makes or reads at a time, and the ids in them at most (or one block)
AT_ONCE, IDS_AT_ONCE = 16, 1 << 20


def code_lengths(counts: np.ndarray, limit: int = LIMIT) -> np.ndarray:
    """Code length per symbol (all counts positive) by package-merge."""
    n = len(counts)
    if n == 1:
        return np.ones(1, np.int64)
    if n > 1 << limit:
        raise ValueError(f"{n} symbols do not fit codes of {limit} bits")
    order = np.argsort(counts, kind="stable")
    leaves = counts[order].astype(np.float64)
    is_leaf, packages = [], np.zeros(0)
    for _ in range(limit):
        merged = np.concatenate([leaves, packages])
        by = np.argsort(merged, kind="stable")
        is_leaf.append(by < n)
        merged = merged[by]
        packages = merged[: len(merged) // 2 * 2].reshape(-1, 2).sum(axis=1)
    lengths, take = np.zeros(n, np.int64), 2 * n - 2
    for level in reversed(is_leaf):
        own = int(level[:take].sum())
        lengths[:own] += 1
        take = 2 * (take - own)
    out = np.empty(n, np.int64)
    out[order] = lengths
    return out


class Codebook:
    def __init__(self, ids: np.ndarray, lengths: np.ndarray):
        order = np.lexsort((ids, lengths))
        self.ids, self.lengths = ids[order].astype(np.int64), lengths[order].astype(np.int64)
        self.limit = int(self.lengths.max()) if len(ids) else 1
        codes, code, last = np.zeros(len(ids), np.int64), 0, 0
        starts = np.flatnonzero(np.diff(self.lengths, prepend=0))
        for at, stop in zip(starts, [*starts[1:], len(ids)][: len(starts)], strict=True):
            code <<= int(self.lengths[at]) - last
            last = int(self.lengths[at])
            codes[at:stop] = code + np.arange(stop - at)
            code += int(stop - at)
        size = int(ids.max()) + 1 if len(ids) else 1
        self.code_of, self.length_of = np.zeros(size, np.uint64), np.zeros(size, np.int64)
        self.code_of[self.ids], self.length_of[self.ids] = codes, self.lengths
        spans = 1 << (self.limit - self.lengths)
        # one look-up for both: the id above the six bits of its code's length
        self.table = np.ones(1 << self.limit, np.uint32 if size <= 1 << 26 else np.uint64)
        self.table[: int(spans.sum())] = np.repeat(self.ids << 6 | self.lengths, spans)

    def encode(self, ids: np.ndarray, every: int = EVERY) -> tuple[bytes, np.ndarray]:
        lengths = self.length_of[ids]
        offsets = np.cumsum(lengths) - lengths
        bits = int(lengths.sum())
        word, at = offsets >> 5, offsets & 31
        value = self.code_of[ids] << (64 - lengths - at).astype(np.uint64)
        n = (bits + 31) // 32 + 1
        # bits of different codes never meet, so sums are unions, exact in doubles
        words = np.bincount(word, (value >> np.uint64(32)).astype(np.float64), n) + np.bincount(word + 1, (value & np.uint64(0xFFFFFFFF)).astype(np.float64), n + 1)[:n]
        return words.astype(np.uint32).astype(">u4").tobytes()[: (bits + 7) // 8], offsets[::every].copy()

    def decode(self, payload: bytes, checkpoints: np.ndarray, n_ids: int, every: int = EVERY) -> np.ndarray:
        return self.decode_all([payload], [checkpoints], [n_ids], every)[0]

    def decode_all(self, payloads: list[bytes], checkpoints: list[np.ndarray], n_ids: list[int], every: int = EVERY) -> list[np.ndarray]:
        """The ids of blocks, all of their stretches side by side."""
        padded = [x + b"\0" * 8 for x in payloads]
        data = np.frombuffer(b"".join(padded), np.uint8).astype(np.uint32)
        window = data[:-3] << np.uint32(24) | data[1:-2] << np.uint32(16) | data[2:-1] << np.uint32(8) | data[3:]
        begins = np.cumsum([0, *map(len, padded)])
        at = np.concatenate([np.asarray(c, np.int64) + 8 * b for c, b in zip(checkpoints, begins, strict=False)])
        out = np.empty((every, len(at)), np.uint32)
        drop, last = np.uint32(32 - self.limit), len(window) - 1
        low, six = self.table.dtype.type(63), self.table.dtype.type(6)
        for k in range(every):
            seen = self.table[(window[np.minimum(at >> 3, last)] << (at & 7).astype(np.uint32)) >> drop]
            out[k] = seen >> six
            at += (seen & low).astype(np.int64)
        ends = np.cumsum([0, *map(len, checkpoints)])
        return [out[:, a:b].T.reshape(-1)[:n] for a, b, n in zip(ends, ends[1:], n_ids, strict=False)]


def together(n_ids: Iterable[int]) -> Iterator[list[int]]:
    """Places of blocks that are read at a time."""
    some: list[int] = []
    ids = 0
    for i, n in enumerate(n_ids):
        if some and (len(some) >= AT_ONCE or ids + n > IDS_AT_ONCE):
            yield some
            some, ids = [], 0
        some.append(i)
        ids += n
    if some:
        yield some


def token_table(docs: DataFrame, path: str, end_id: int) -> DataFrame:
    """doc_id, ids: 16-bit where the vocabulary allows it, else 32-bit."""
    kind = id_kind(path)

    def encode(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tokens, end = tokenizer(path), np.array([end_id], "<u4").tobytes()
        for frame in frames:
            ids = [np.frombuffer(tokens.ids(t) + end, "<u4").astype(kind).tobytes() for t in frame["text"]]
            yield pd.DataFrame({"doc_id": frame["doc_id"], "ids": ids})

    return docs.select(id_as_string(docs, "doc_id"), "text").mapInPandas(encode, "doc_id string, ids binary").withColumn("doc_id", id_back(docs, "doc_id"))


def id_kind(path: str) -> str:
    return "<u2" if tokenizer(path).size <= 1 << 16 else "<u4"


def id_counts(tokens: DataFrame, kind: str) -> pd.DataFrame:
    """id, n over the whole corpus: as many rows as the vocabulary at most."""

    def count(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros(0, np.int64)
        for frame in frames:
            seen = np.bincount(np.frombuffer(b"".join(frame["ids"]), kind), minlength=len(total))
            seen[: len(total)] += total
            total = seen
        ids = np.flatnonzero(total)
        yield pd.DataFrame({"id": ids.astype(np.int64), "n": total[ids]})

    return tokens.mapInPandas(count, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toPandas()


def write_ids(docs: DataFrame, path: str, to: str | None = None, end_id: int = 1, limit: int = LIMIT, every: int = EVERY, block_ids: int = BLOCK_IDS) -> str:
    """Writes the format and returns its folder (by default a new one in the shared folder)."""
    spark = docs.sparkSession
    to = to or f"{shared_folder(spark)}/ids-{uuid.uuid4().hex}"
    kind = id_kind(path)
    tokens = written(token_table(docs, path, end_id), "tokens")
    counts = id_counts(tokens, kind)
    ids = counts["id"].to_numpy(np.int64)
    lengths = code_lengths(counts["n"].to_numpy(np.int64), limit) if len(ids) else np.zeros(0, np.int64)
    spark.createDataFrame(pd.DataFrame({"id": ids, "length": lengths}), "id long, length long").coalesce(1).write.parquet(f"{to}/codebook")
    book = spark.sparkContext.broadcast((ids, lengths))
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def blocks(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codes, part, block = Codebook(*book.value), TaskContext.get().partitionId(), 0
        doc_ids: list = []
        arrays: list[np.ndarray] = []
        rows: list[tuple] = []
        held = ready = 0

        def row() -> tuple:
            all_ = np.concatenate(arrays)
            payload, checkpoints = codes.encode(all_, every)
            return part, block, doc_ids, [len(a) for a in arrays], len(all_), checkpoints, payload

        def frame_of(rows: list[tuple]) -> pd.DataFrame:
            return pd.DataFrame(dict(zip(("part", "block", "doc_ids", "lengths", "n_ids", "checkpoints", "payload"), map(list, zip(*rows, strict=True)), strict=True)))

        for frame in frames:
            for doc_id, data in zip(frame["doc_id"], frame["ids"], strict=True):
                doc_ids.append(doc_id)
                arrays.append(np.frombuffer(data, kind))
                held += len(arrays[-1])
                if held >= block_ids:
                    rows.append(row())
                    ready += held
                    doc_ids, arrays, held, block = [], [], 0, block + 1
                    if len(rows) >= AT_ONCE or ready >= IDS_AT_ONCE:
                        yield frame_of(rows)
                        rows, ready = [], 0
        if arrays:
            rows.append(row())
        if rows:
            yield frame_of(rows)

    schema = "part int, block long, doc_ids array<string>, lengths array<long>, n_ids long, checkpoints array<long>, payload binary"
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("ids").asc(), F.col("ids").asc()]  # an id that many rows repeat is split by its ids' hash
    dealt = tokens.repartitionByRange(*order[:2]).sortWithinPartitions(*order).select(id_as_string(tokens, "doc_id"), "ids")
    dealt.mapInPandas(blocks, schema).withColumn("doc_ids", F.col("doc_ids").cast(f"array<{id_type}>")).write.parquet(f"{to}/blocks")
    forget(tokens)
    return to


def read_ids(spark: SparkSession, folder: str, every: int = EVERY, keep_ids: bool = True) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 and ids (little-endian unsigned 32-bit), decoded from the files."""
    blocks = spark.read.parquet(f"{folder}/blocks")
    book = spark.read.parquet(f"{folder}/codebook").toPandas()
    shared = spark.sparkContext.broadcast((book["id"].to_numpy(np.int64), book["length"].to_numpy(np.int64)))
    id_type = blocks.schema["doc_ids"].dataType.elementType.simpleString()

    def decode(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codes = Codebook(*shared.value)
        for frame in frames:
            for some in together(frame["n_ids"]):
                blocks = frame.iloc[some]
                parts: list[list[np.ndarray]] = [[] for _ in range(5)]
                data: list[bytes] = []
                decoded = codes.decode_all(list(blocks["payload"]), list(blocks["checkpoints"]), list(blocks["n_ids"]), every)
                for part, block, doc_ids, lengths, ids in zip(blocks["part"], blocks["block"], blocks["doc_ids"], blocks["lengths"], decoded, strict=True):
                    ids, lengths = ids.astype("<u4"), np.asarray(lengths, np.int64)
                    within = np.cumsum(lengths) - lengths
                    data += [ids[s : s + k].tobytes() for s, k in zip(within, lengths, strict=True)]
                    for held, x in zip(parts, (np.asarray(doc_ids, object), np.full(len(lengths), part), np.full(len(lengths), block), within, lengths), strict=True):
                        held.append(x)
                doc_ids, part, block, within, lengths = map(np.concatenate, parts)
                out = pd.DataFrame({"doc_id": doc_ids, "part": part, "block": block, "within": within, "n_tokens": lengths, "ids_crc32": [zlib.crc32(x) for x in data]})
                yield out.assign(ids=data) if keep_ids else out

    read = blocks.select("part", "block", F.col("doc_ids").cast("array<string>").alias("doc_ids"), "lengths", "n_ids", "checkpoints", "payload")
    rows = read.mapInPandas(decode, f"doc_id string, part int, block long, within long, n_tokens long, ids_crc32 long{', ids binary' * keep_ids}")
    sizes = blocks.select("part", "block", "n_ids")
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n"))
    up_to = lambda *by: (Window.partitionBy(*by) if by else Window.partitionBy())
    before = lambda c, w: F.coalesce(F.sum(c).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # one row per partition of the writer, which is a number of the session and not of the data
    bases = parts.select("part", before("n", up_to().orderBy("part")).alias("part_base"))
    inner = sizes.select("part", "block", before("n_ids", up_to("part").orderBy("block")).alias("block_base"))
    base = inner.join(bases, "part").select("part", "block", (F.col("part_base") + F.col("block_base")).alias("base"))
    out = rows.join(base, ["part", "block"])
    return out.select(F.col("doc_id").cast(id_type).alias("doc_id"), (F.col("base") + F.col("within")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * keep_ids)
