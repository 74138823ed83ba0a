"""Operators against second implementations, and the plans they promise."""

import hashlib
import itertools
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from hopwise.llm import chat_format, html_extraction, packing, pii, quality_classifier, quality_rules, repeated_bytes


def words(rng, n, vocabulary=400):
    return [f"v{rng.randrange(vocabulary)}" for _ in range(n)]


# ---- op 1: pages built around a known article


def page(rng):
    text = lambda lo, hi: " ".join(words(rng, rng.randrange(lo, hi)))
    blocks = [text(12, 60) for _ in range(rng.randrange(2, 8))]
    title = text(3, 8)
    inside = "".join(f"<p>{b}</p>" if rng.random() < 0.8 else f"<ul><li>{b}</li></ul>" for b in blocks)
    wrapper = rng.choice(["article", "main", "div class='post comments-open'", "div id='content'", "section class='layout has-sidebar'"])
    tag = wrapper.split()[0]
    links = "".join(f"<li><a href='/{k}'>{text(1, 3)}</a></li>" for k in range(rng.randrange(3, 9)))
    noise = [f"<nav><ul>{links}</ul></nav>", f"<div class='sidebar'><h3>{text(1, 3)}</h3><ul>{links}</ul></div>", f"<div class='cookie-notice'>{text(5, 15)}</div>", f"<aside>{text(5, 20)}</aside>", f"<form><label>{text(1, 3)}</label><input></form>", f"<script>var a = '{text(3, 9)}'</script>"]
    rng.shuffle(noise)
    cut = rng.randrange(len(noise) + 1)
    comments = f"<section class='comments'><p>{text(5, 12)}</p></section>" if rng.random() < 0.5 else ""
    html = f"<html><head><title>{text(2, 5)}</title><style>p {{}}</style></head><body><header>{text(1, 4)}</header>{''.join(noise[:cut])}<{wrapper}><h1>{title}</h1>{inside}</{tag}>{comments}{''.join(noise[cut:])}<footer>{text(3, 9)}</footer></body></html>"
    return html, "\n".join([title, *blocks])


def test_html_gives_the_article_that_the_page_was_built_around():
    rng = random.Random(11)
    for _ in range(150):
        html, want = page(rng)
        assert html_extraction.main_text(html) == want, html


def test_class_names_do_not_empty_an_article():
    line = "A long enough paragraph of the article, with many words in it, so that it is content."
    body = f"<p>{line}</p><p>{line}</p>"
    for html in (f"<div class='layout has-sidebar'><article>{body}</article></div>", f"<div class='post comments-open'>{body}</div>", f"<div class='promo-widget'>{body}</div>"):
        assert html_extraction.main_text(html) == f"{line}\n{line}"


# ---- op 3: the plan


def test_a_filter_does_not_copy_the_windows(spark):
    docs = spark.createDataFrame([(i, " ".join(words(random.Random(i), 90)), "s") for i in range(20)], "doc_id long, text string, source string")
    plan = lambda df: df._jdf.queryExecution().optimizedPlan().toString()
    whole = quality_rules.quality_rules(docs)
    assert plan(whole.where("kept")).count("sort_array") == plan(whole).count("sort_array") == 0  # worked on a written table
    assert "Python" not in whole._jdf.queryExecution().executedPlan().toString()
    assert quality_rules.kept_documents(docs).count() == 20


# ---- op 4: against all ways to pack


def fewest(counts, capacity):
    """By trying every bin for every piece, largest first."""
    pieces = sorted((s for s, n in counts.items() for _ in range(n)), reverse=True)
    best = [len(pieces)]

    def place(i, rooms):
        if len(rooms) >= best[0]:
            return
        if i == len(pieces):
            best[0] = len(rooms)
            return
        for k in {r: k for k, r in enumerate(rooms) if r >= pieces[i]}.values():
            place(i + 1, [*rooms[:k], rooms[k] - pieces[i], *rooms[k + 1 :]])
        place(i + 1, [*rooms, capacity - pieces[i]])

    place(0, [])
    return best[0]


def test_packing_without_a_budget_is_exact():
    rng = random.Random(6)
    for _ in range(200):
        counts = {rng.randint(2, 14): rng.randint(1, 3) for _ in range(4)}
        found = packing.search(counts, 15, None)
        held = Counter()
        for n, content in found.patterns:
            for s, k in content:
                held[s] += n * k
        assert held == Counter(counts) and found.proven and found.bound <= found.bins == fewest(counts, 15), counts


# ---- op 5: passages by words, and both ways of counting


@pytest.mark.parametrize("most", [2048, 1])
def test_shared_windows_against_all_windows(spark, most):
    rng = random.Random(9)
    passages = [words(rng, n, 10**6) for n in (8, 12, 15, 40)]
    texts = []
    for i in range(60):
        own = words(rng, rng.randrange(5, 40), 10**6)
        texts.append((i, " ".join([*own, *(rng.choice(passages) if i % 2 else []), *words(rng, 6, 10**6)])))
    texts += [(100, texts[3][1]), (101, texts[3][1]), (102, None), (None, "a b"), (104, " ".join(passages[3] * 3)), (105, " ".join(["x"] * 50))]
    k, seen = 10, {}
    for n, (_, t) in enumerate(texts):
        w = (t or "").split()
        for s in range(len(w) - k + 1):
            seen.setdefault(tuple(w[s : s + k]), []).append(n)
    counts = Counter(n for at in seen.values() if len(set(at)) > 1 for n in at)
    want = sorted((i or -1, counts[n]) for n, (i, _) in enumerate(texts))
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    got = repeated_bytes.remove_repeats(docs, 60, 40, most, passage_words=k).collect()
    assert sorted((r["doc_id"] or -1, r["n_shared_windows"]) for r in got) == want
    data, length, places = [(t or "").encode() for _, t in texts], 60, {}
    for n, b in enumerate(data):
        for s in range(len(b) - length + 1):
            places.setdefault(b[s : s + length], []).append((n, s))
    marks = [np.zeros(len(b), bool) for b in data]
    for at in places.values():
        for n, s in at if len(at) > 1 else ():
            marks[n][s : s + length] = True
    want = sorted((i or -1, int(m.sum()), hashlib.sha256(np.frombuffer(b, np.uint8)[~m].tobytes()).hexdigest()) for (i, _), b, m in zip(texts, data, marks, strict=True))
    assert sorted((r["doc_id"] or -1, r["n_removed"], r["kept_sha256"]) for r in got) == want


def test_string_ranks_are_the_order_of_suffixes():
    rng = random.Random(1)
    for length in (1, 5, 7, 8, 30, 33):
        data = bytes(rng.choice(b"ab") for _ in range(200))
        rank = repeated_bytes.string_ranks(np.frombuffer(data, np.uint8), length)
        strings = [data[i : i + length] for i in range(len(data) - length + 1)]
        order = {x: i for i, x in enumerate(sorted(set(strings)))}
        assert rank.tolist() == [order[x] for x in strings]


# ---- op 7: base spans by the plain patterns, and planted disguises


def test_base_spans_are_those_of_the_patterns():
    rng = random.Random(3)
    for _ in range(4000):
        text = "".join(rng.choice("ab1.@_-% +()4") for _ in range(rng.randrange(40)))
        want = [(k, *m.span()) for k in pii.KINDS for m in re.finditer(pii.PATTERNS[k], text) if pii.valid(k, m[0])]
        assert pii.base_spans(text) == want, text


def test_planted_disguises_are_found_where_they_are(spark):
    rng = random.Random(5)
    digits = dict(zip("0123456789", "zero one two three four five six seven eight nine".split(), strict=True))
    ways = {
        "email": [lambda: "ann.lee@mail.example.org", lambda: "ann.lee [at] mail [dot] example [dot] org", lambda: "ann.lee(at)example(dot)org", lambda: "ann.lее@example.org", lambda: "ann.lee at example dot org"],
        "ip": [lambda: "10.20.30.40", lambda: "１０.20.30.40", lambda: "10․20․30․40"],
        "card": [lambda: "4111 1111 1111 1111", lambda: "４１１１ 1111 1111 1111"],
        "phone": [lambda: "+49 30 1234567", lambda: "plus " + " ".join(digits[c] for c in "4930123456")],
    }
    rows, want = [], {}
    for i in range(120):
        kind = rng.choice(list(ways))
        secret = rng.choice(ways[kind])()
        before, behind = " ".join(words(rng, 6)) + ": ", " ; " + " ".join(words(rng, 6))
        rows.append((i, before + secret + behind))
        want[i] = f"{kind}:{len(before)}:{len(before) + len(secret)}"
    got = {r["doc_id"]: r for r in pii.find_pii(spark.createDataFrame([*rows, (None, None)], "doc_id long, text string")).collect()}
    assert {i: got[i]["spans"] for i in want} == want and got[None]["n_spans"] == 0
    clean = pii.redact_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(re.search(r"<(EMAIL|IP|CARD|PHONE)>", r["text"]) for r in clean)


# ---- op 8: a conversation over many tasks


def test_a_long_conversation_is_spread_over_tasks(spark):
    rows = [(7, t, "assistant" if t % 2 else "user", f"turn {t}") for t in range(3000)] + [(c, 0, "assistant", "x") for c in (1, 9)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(5)
    segments = chat_format.format_conversations(turns)
    mine = segments.where("conv_id = 7").collect()
    assert sorted(r["place"] for r in mine) == list(range(3000)) and all(r["place"] == r["turn"] for r in mine)
    assert [r["turn"] for r in segments.collect() if r["segment"].startswith("<s>")].count(0) == 3
    assert sum(r["segment"].startswith("<s>") for r in mine) == 1
    assert all(r["segment"][r["loss_start"] : r["loss_end"]] == (f"turn {r['turn']}" if r["turn"] % 2 else "") for r in mine)
    got = {r["conv_id"]: r for r in chat_format.conversation_digests(segments).collect()}
    said = "".join(f"{r[2]}\n{r[3]}\n" for r in rows if r[0] == 7)
    assert got[7]["turns_sha256"] == hashlib.sha256(said.encode()).hexdigest() and got[7]["n_turns"] == 3000


# ---- op 9: word order counts, and held-out rows


def test_word_order_is_learned_and_held_out_rows_are_right(spark):
    rng = random.Random(4)
    steps = "first take the pan then heat some oil then add one egg and stir it".split()
    rows = []
    for i in range(300):
        text = [w for _ in range(6) for w in steps]
        if i % 2 == 0:  # the same words in no order
            rng.shuffle(text)
        rows.append((i, " ".join(text)))
    labels = spark.createDataFrame([(i, i % 2) for i in range(300)], "doc_id long, quality int")
    got = quality_classifier.classify(spark.createDataFrame(rows, "doc_id long, text string"), labels, buckets=1 << 14).collect()
    held = [r for r in got if r["held_out"]]
    assert len(held) == sum(zlib.crc32(str(i).encode()) % 3 == 1 for i in range(300))
    assert np.mean([r["predicted"] == r["doc_id"] % 2 for r in held]) >= 0.95


def test_scores_are_the_softmax_of_the_mean_vector():
    rng = random.Random(2)
    rows = [(" ".join(words(rng, 30, 50)), k % 2) for k in range(40)]
    model = quality_classifier.train(rows, buckets=1 << 8, epochs=2)
    line, bias = model.line()
    line, size = line.astype(float), model.buckets
    back = quality_classifier.BACK
    texts = [t for t, _ in rows] + ["", None, "one"]
    got = quality_classifier.score_texts(texts, quality_classifier.WordTable(line[:size], size), line[size : size + back], line[size + back :], bias)
    for text, score in zip(texts, got, strict=True):
        w = (text or "").split()
        hashes = [quality_classifier.xxhash.xxh64_intdigest(x) for x in w]
        units = [model.vectors[quality_classifier.buckets_of(x, size)].mean(axis=0) for x in w]
        units += [model.vectors[size + k - 1] for i, k in itertools.product(range(len(w)), range(1, back + 1)) if i >= k and w[i] == w[i - k]]
        units += [model.vectors[size + back + b] for b in quality_classifier.runs_of(np.array(hashes, np.uint64), size)] if w else []
        z = model.weights @ (np.mean(units, axis=0) if units else np.zeros(model.weights.shape[1])) + model.bias
        assert abs(score - np.exp(z[1]) / np.exp(z).sum()) < 1e-5
