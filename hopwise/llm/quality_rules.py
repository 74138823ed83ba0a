"""Quality rules on documents, with functions of Spark SQL alone.

Each text gets its own counts (words, symbols, repeated lines, words in repeated three-word windows) and a
verdict of the corpus: lines are normalised and hashed, the distinct documents that show a line are counted
for each host, lines above the limits are taken out, and a document of which too little is left is rejected.

Decisions
* The host is the column ``source``; null is a host of its own.
* A document is one row. Lines of any length are counted. In the count of documents a line has, copies (equal
  texts) count once: a group of copies is no boilerplate, and near-duplicate removal is there for it.
* A line is frequent at a host if more than ``max_documents`` documents and more than ``max_share`` of the
  documents of the host show it. Removed lines are only counted; texts are not changed.
* Null, empty and blank texts have no words and fail the base rules. Ties can't arise. Rows that repeat get
  equal results. An empty table gives an empty table. Other columns are ignored, whatever their names.

One pass reads the texts: counts and hashed lines of each go to a table, and the rest works on that. Nothing here
collects a group: windows live in arrays of their own row, bound once, counts combine before the shuffle, the lines
of documents meet the frequent lines in a join whose large keys adaptive execution can split.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import once, row_key, text_key, written

WORD = r"[^\x20\x09-\x0D]+"
SYMBOL = r"[#*$%&|<>]"
COLUMNS = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]


def repeated_words(words: Column) -> Column:
    """How many of the words stand in three-word windows found twice or more.

    Windows are hashed and sorted with their places; those with an equal neighbour are repeated, and their places,
    in order, tell the words they cover.
    """

    def windows(h: Column) -> Column:
        at = F.sequence(F.lit(0), F.size(h) - 3)
        return F.sort_array(F.transform(at, lambda i: F.struct(F.xxhash64(F.get(h, i), F.get(h, i + 1), F.get(h, i + 2)).alias("k"), i.alias("p"))))

    def places(s: Column) -> Column:
        key = lambda j: F.get(s, j)["k"]
        twice = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda j: key(j).eqNullSafe(key(j - 1)) | key(j).eqNullSafe(key(j + 1)))
        return F.sort_array(F.transform(twice, lambda j: F.get(s, j)["p"]))

    def covered(starts: Column) -> Column:
        return F.aggregate(
            starts,
            F.struct(F.lit(-3).alias("last"), F.lit(0).alias("sum")),
            lambda a, p: F.struct(p.alias("last"), (a["sum"] + F.least(F.lit(3), p - a["last"])).alias("sum")),
            lambda a: a["sum"],
        )

    hashes = F.transform(words, lambda x: F.xxhash64(x))
    found = once(hashes, lambda h: F.when(F.size(h) >= 3, once(windows(h), lambda s: covered(places(s)))))
    return F.coalesce(found, F.lit(0))


def own_counts() -> list[Column]:
    """The counts of the text ``t`` alone."""
    words = F.regexp_extract_all("t", F.lit(WORD), F.lit(0))
    of_words = once(words, lambda w: F.struct(F.size(w).alias("n"), F.char_length(F.array_join(w, "")).alias("chars"), repeated_words(w).alias("repeated")))
    lines = F.filter(F.split("t", "\n", -1), lambda x: x.rlike(WORD))
    return [
        of_words.alias("words"),
        F.regexp_count("t", F.lit(SYMBOL)).cast("long").alias("n_symbols"),
        once(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
    ]


def normalised_lines() -> Column:
    """line (128 bits of the normalised line) and words, for each line of ``t`` with a word."""
    # lower-case A-Z, digits as 0, white space as one space
    plain = F.regexp_replace(F.translate("t", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), "[0-9]", "0")
    words = F.transform(F.split(plain, "\n", -1), lambda x: F.regexp_extract_all(x, F.lit(WORD), F.lit(0)))
    return F.transform(F.filter(words, lambda x: F.size(x) > 0), lambda x: F.struct(text_key(F.array_join(x, " ")).alias("line"), F.size(x).alias("words")))


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, key, host, doc, the base counts, lines: one pass over the texts, written, so that nothing after reads a text.

    ``key`` numbers the rows of the written table.
    """
    text = docs.select("doc_id", F.coalesce("source", F.lit("")).alias("host"), F.coalesce("text", F.lit("")).alias("t"))
    made = text.select("doc_id", F.monotonically_increasing_id().alias("key"), "host", text_key("t").alias("doc"), *own_counts(), normalised_lines().alias("lines"))
    table = written(made, "digests")
    return table.select(
        "doc_id", "key", "host", "doc", F.col("words.n").cast("long").alias("n_words"), F.col("words.chars").cast("long").alias("word_chars"),
        "n_symbols", "n_dup_lines", F.col("words.repeated").cast("long").alias("n_repeat_words"), "lines",
    )


def frequent_lines(digest: DataFrame, max_documents: int, max_share: float) -> DataFrame:
    """host, line, documents: the lines above both limits."""
    distinct = digest.select("host", "doc", F.explode("lines.line").alias("line")).distinct()
    counts = distinct.groupBy("host", "line").agg(F.count("*").alias("documents")).where(F.col("documents") > max_documents)
    size = digest.groupBy("host").agg(F.count("*").alias("size"))
    return counts.join(size, "host").where(F.col("documents") > max_share * F.col("size")).select("host", "line", "documents")


def quality_rules(
    docs: DataFrame, max_documents: int = 20, max_share: float = 0.002, least_left: float = 0.3, least_words: int = 50, most_repeated: int = 50
) -> DataFrame:
    """COLUMNS and n_removed_words: a row per row of ``docs(doc_id, source, text)``."""
    digest = digests(docs)
    frequent = frequent_lines(digest, max_documents, max_share)
    lines = digest.select("key", "host", F.explode("lines").alias("l")).select("key", "host", "l.line", "l.words")
    removed = lines.join(frequent.select("host", "line"), ["host", "line"]).groupBy("key").agg(F.sum("words").alias("n_removed_words"))
    failed = (F.col("n_words") < least_words) | (100 * F.col("n_repeat_words") > most_repeated * F.col("n_words"))
    left = F.col("n_words") - F.col("n_removed_words")
    return (
        digest.drop("lines", "host", "doc")
        .join(removed, "key", "left")
        .withColumn("n_removed_words", F.coalesce("n_removed_words", F.lit(0)).cast("long"))
        .withColumn("base_failed", failed)
        .withColumn("kept", ~failed & (left >= least_left * F.col("n_words")))
        .select(*COLUMNS, "n_removed_words")
    )


def kept_documents(docs: DataFrame, **limits) -> DataFrame:
    """The rows of ``docs`` that pass, with all their columns."""
    key = row_key("doc_id", "source", "text")
    verdicts = quality_rules(docs.withColumn("doc_id", key), **limits).where("kept").select(F.col("doc_id").alias("_key")).distinct()
    return docs.withColumn("_key", key).join(verdicts, "_key", "left_semi").drop("_key")
