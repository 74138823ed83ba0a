"""Ids that doubles can't hold beside nulls, and texts made to be slow, through every operator that has a Python worker."""

import time

import pytest

from hopwise.llm import chat_format, decontamination, html_extraction, huffman_ids, near_duplicates, packing, pii, quality_classifier, quality_rules, queries, repeated_bytes

BIG = 2**53 + 1
IDS = [BIG, None, -BIG - 2, 2**63 - 1]


@pytest.fixture(scope="module")
def docs(spark):
    text = " ".join(f"word{i}" for i in range(80))
    rows = [(i, None if k == 3 else f"{text} {k}", "s") for k, i in enumerate(IDS)] + [(BIG + 2, f"{text} 0", "s")]
    return spark.createDataFrame(rows, "doc_id long, text string, source string").coalesce(1)


def ids(df, name="doc_id"):
    return sorted((r[name] for r in df.select(name).distinct().collect()), key=lambda x: (x is not None, x))


def test_ids_come_back_as_they_were(spark, docs):
    want = sorted({*IDS, BIG + 2}, key=lambda x: (x is not None, x))
    bench = spark.createDataFrame([(1, "word1 word2 word3")], "item_id long, text string")
    labels = spark.createDataFrame([(BIG, 1), (2**63 - 1, 0)], "doc_id long, quality int")
    for block in (200_000, 1):
        assert ids(decontamination.decontaminate(docs, bench, block_windows=block)) == want
    assert ids(quality_rules.quality_rules(docs)) == want
    assert ids(packing.pack_documents(docs, queries.BYTE_BPE)) == want
    assert ids(repeated_bytes.remove_repeats(docs, passage_words=50)) == want
    assert ids(huffman_ids.read_ids(spark, huffman_ids.write_ids(docs, queries.WORD_BPE))) == want
    assert ids(pii.find_pii(docs)) == want
    assert ids(quality_classifier.classify(docs, labels, buckets=1 << 10)) == want
    found = near_duplicates.near_duplicates(docs)
    assert ids(found) == want
    # copies and near copies are found across such ids, and the class id is exact
    assert {r["class_id"] for r in found.where("doc_id in (9007199254740993, 9007199254740995, -9007199254740995)").collect()} == {-BIG - 2}
    chat = spark.createDataFrame([(i, t, "user", "hi") for i in IDS for t in (None, BIG)], "conv_id long, turn long, role string, text string").coalesce(1)
    assert ids(chat_format.format_and_read_back(chat), "conv_id") == sorted(IDS, key=lambda x: (x is not None, x))
    assert ids(chat_format.format_conversations(chat), "turn") == [None, BIG]
    pages = spark.createDataFrame([(i, None, "<p>x</p>") for i in IDS], "page_id long, url string, html string").coalesce(1)
    assert ids(html_extraction.extract_pages(pages), "page_id") == sorted(IDS, key=lambda x: (x is not None, x))


N = 40_000


@pytest.mark.parametrize("text", [" " * N + "[at]", "a" * N + " @", "a" * N, "1" * N, "1.1.1." + "1" * N, "+1" + " " * N, "one " * 10_000, "a dot" + " " * N + "b", "a@" * 10_000, "a@b.cc " * 5_000, "jo at b dot com " * 2_500, "one" + " " * N + "two", "a" + "-" * N + "at", "[" * N])
def test_pii_takes_time_in_proportion(text):
    began = time.perf_counter()
    pii.all_spans(text)
    assert time.perf_counter() - began < 3


@pytest.mark.parametrize("html", ["<div>" * N + "x" + "</div>" * N, "<b>" * N + "</i>" * N + "x", "<div class=ad>" * 10_000 + "x", "<p>" + "a " * 200_000, "<p " * 20_000, "<!--" * 20_000, "<a b='" * 5_000, "<div><p>hello there</p>" * 10_000])
def test_html_takes_time_in_proportion(html):
    began = time.perf_counter()
    html_extraction.main_text(html)
    assert time.perf_counter() - began < 5


def test_long_texts_through_the_tables(spark):
    line = " ".join(f"token{i % 5000}" for i in range(60_000))
    docs = spark.createDataFrame([(1, line, "s"), (2, "\n".join([line[:3000]] * 100), "s")], "doc_id long, text string, source string")
    got = {r["doc_id"]: r for r in quality_rules.quality_rules(docs).collect()}
    assert got[1]["n_words"] == 60_000 and got[1]["n_repeat_words"] == 60_000 and got[2]["n_dup_lines"] == 99
    assert pii.find_pii(docs).count() == 2
    labels = spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, quality int")
    assert quality_classifier.classify(docs, labels, buckets=1 << 10).count() == 2
    chat = spark.createDataFrame([(1, 1, "user", line * 5)], "conv_id long, turn long, role string, text string")
    assert chat_format.format_and_read_back(chat).first()["formatted_chars"] > 5 * len(line)
    assert {r["doc_id"]: r["n_words"] for r in decontamination.decontaminate(docs, spark.createDataFrame([(1, line[:400])], "item_id long, text string")).collect()}[1] == 60_000
