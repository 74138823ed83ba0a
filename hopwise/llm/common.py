"""What the operators of this subpackage share: working folders, hidden row keys, word tables."""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.store import forget, shared_folder, written

__all__ = ["WordHashes", "forget", "hot_join", "id_as_string", "id_back", "mixed", "once", "row_key", "shared_folder", "table", "text_key", "written"]

def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_key(value: Column | str) -> Column:
    """128 bits (MD5) of a string; null is the empty string."""
    value = F.col(value) if isinstance(value, str) else value
    return F.unhex(F.md5(F.coalesce(value, F.lit(""))))


def row_key(*columns: str) -> Column:
    """128 bits of a row, by default of its id and text. Rows that repeat share it, and get the same result."""
    parts = [F.coalesce(F.concat(F.lit("="), F.col(c).cast("string")), F.lit("")) for c in columns or ("doc_id", "text")]
    return text_key(F.concat_ws("\x1f", *parts))


def once(value: Column, use) -> Column:
    """``use(value)`` with the value bound to a lambda's variable: no rule of the optimiser can copy it to each of its uses."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


class WordHashes(dict):
    """word -> 64-bit hash, kept for the words met lately; emptied when full, so its size is bounded."""

    def __init__(self, most: int = 400_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: str) -> int:
        if len(self) >= self.most:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
        return value

    def of(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (shift, multiply, shift), so that neighbouring inputs look unrelated."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def id_as_string(docs: DataFrame, name: str) -> Column:
    """An id on its way through a Python worker: as a string, since pandas turns integers beside nulls into doubles."""
    binary = docs.schema[name].dataType.simpleString() == "binary"
    return (F.hex(name) if binary else F.col(name).cast("string")).alias(name)


def id_back(docs: DataFrame, name: str) -> Column:
    """The id as the type it had in ``docs``."""
    kind = docs.schema[name].dataType
    return (F.unhex(name) if kind.simpleString() == "binary" else F.col(name).cast(kind)).alias(name)


def hot_join(rows: DataFrame, sizes: DataFrame, keys: list[str], size: str, spread: list[str], salts: int = 16) -> DataFrame:
    """``rows`` inner-joined to ``sizes`` (one row for each of ``keys``, with how many rows have it in ``size``).

    Keys above a 512th of all rows counted are hot: at most 512, so their hashes are a short list. Rows of a hot key
    are dealt by a hash of ``spread`` to ``salts`` copies of its row in ``sizes``, so that no task gets a hot key alone.
    Both sides tell hot keys by the same hash: one that is taken for hot by mistake is only dealt, too.
    """
    sizes = written(sizes, "sizes")
    total = sizes.agg(F.sum(size)).first()[0] or 0
    hot = [r["h"] for r in sizes.where(F.col(size) > max(1, total // 512)).select(F.xxhash64(*keys).alias("h")).collect()]
    is_hot = F.xxhash64(*keys).isin(hot or [0])  # one plan, with hot keys or without
    salt = F.when(is_hot, F.pmod(F.xxhash64(*spread), F.lit(salts)).cast("int")).otherwise(0)
    copies = F.when(is_hot, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
    return rows.withColumn("_salt", salt).join(sizes.withColumn("_salt", F.explode(copies)), [*keys, "_salt"]).drop("_salt")
