"""The graph of near-duplicates: representatives at a similarity of 0.8 or more, copies linked to theirs, no 5-gram too common."""

import itertools

from hopwise.sources import graphs

LETTERS = "abcdefghijklmnopqrstuvwxyz"


def word(i, j):
    return "q" + LETTERS[i // 26] + LETTERS[i % 26] + LETTERS[j // 26] + LETTERS[j % 26]


def test_links_are_those_of_brute_force(spark, tmp_path):
    own = lambda i, n=12: " ".join(word(i, j) for j in range(n))
    texts = [(i, own(i) + " one passage that all of these documents share") for i in range(60)]
    texts += [(100 + i, own(200).upper()) for i in range(55)]  # copies
    texts += [(200, own(201)), (201, "four words are few"), (202, "four words are few"), (203, None), (204, "")]
    for i in range(70):  # a long common text, with up to nine words changed: pairs on both sides of 0.8
        w = own(300, 100).split()
        for k in range(i % 10):
            w[(i * 7 + 11 * k) % 100] = word(301 + i, k)
        texts.append((300 + i, " ".join(w)))
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    words = {i: (t or "").lower().split() for i, t in texts}
    least: dict[tuple, int] = {}
    for i, w in words.items():
        if len(w) >= 5:
            least[tuple(w)] = min(i, least.get(tuple(w), i))
    grams = {rep: {w[k : k + 5] for k in range(len(w) - 4)} for w, rep in least.items()}
    want = {(a, b) for a, b in itertools.permutations(grams, 2) if 10 * len(grams[a] & grams[b]) >= 8 * len(grams[a] | grams[b])}
    similar = len(want)
    want |= {p for i, w in words.items() if len(w) >= 5 and (rep := least[tuple(w)]) != i for p in ((i, rep), (rep, i))}
    got = graphs.near_duplicate(spark, str(tmp_path)).edges.collect()
    assert len(got) == len(want) and {tuple(r) for r in got} == want
    assert 50 < similar < len(grams) * (len(grams) - 1) and not any(a < 60 for a, _ in want)
    assert sum(a == 100 for a, _ in want) == 54  # a star of copies, not all pairs
