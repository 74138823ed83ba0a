"""op6: most of a text is not cut again, and blocks are written and read several at a time."""

import random

import numpy as np
import pytest

from hopwise.llm import huffman_ids as H
from hopwise.llm import tokens as T
from hopwise.llm.queries import WORD_BPE


@pytest.mark.parametrize("most", [4, 400_000])
def test_runs_have_the_ids_of_the_library(most):
    r, tk = random.Random(7), T.TextTokenizer(WORD_BPE, most)
    letters = [*map(chr, range(256)), *" ab'sT\n1\x1c\x85\xa0" * 30]
    for n in range(1500):
        text = "".join(r.choices(letters, k=r.randrange(80)))
        assert tk.ids(text) == np.array(tk.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes(), repr(text)
        assert len(tk.pieces) <= most + 1  # a run comes after its pieces


def test_words_met_again_are_not_cut(monkeypatch):
    tk = T.TextTokenizer(WORD_BPE)
    first = tk.ids("don't stop, don't stop 2nd")
    tk.pieces.cut = None
    assert tk.ids("don't stop, don't stop 2nd") == first


def test_blocks_are_decoded_together():
    r = np.random.default_rng(3)
    arrays = [r.geometric(0.01, n).astype(np.int64) for n in (1, 5000, 127, 128, 129, 40_000)]
    ids, counts = np.unique(np.concatenate(arrays), return_counts=True)
    book = H.Codebook(ids, H.code_lengths(counts))
    packed = [book.encode(a) for a in arrays]
    for a, b in zip(book.decode_all([p for p, _ in packed], [c for _, c in packed], [len(a) for a in arrays]), arrays, strict=True):
        assert (a == b).all()


def test_blocks_at_a_time():
    assert list(H.together([])) == [] and list(H.together([H.IDS_AT_ONCE * 3, 1, 1])) == [[0], [1, 2]]
    assert [len(x) for x in H.together([1] * (2 * H.AT_ONCE + 1))] == [H.AT_ONCE, H.AT_ONCE, 1]


def test_small_blocks_give_the_same_rows(spark, tmp_path):
    docs = spark.createDataFrame([(i, "so many words, " * (i % 40)) for i in range(400)] + [(None, None)], "doc_id long, text string").repartition(3)
    rows = [sorted(map(str, H.read_ids(spark, H.write_ids(docs, WORD_BPE, f"{tmp_path}/{n}", block_ids=n)).collect())) for n in (50, 1 << 16)]
    assert rows[0] == rows[1] and len(rows[0]) == 401
