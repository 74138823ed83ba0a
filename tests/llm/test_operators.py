import hashlib
import itertools
import random
import zlib

import numpy as np
import public_tokenizers
import pytest

from hopwise.llm import chat_format, decontamination, html_extraction, huffman_ids, near_duplicates, packing, pii, quality_classifier, quality_rules, queries, repeated_bytes

DOCS = "doc_id long, text string, lang string, source string, n_chars long, word string, key string, n long"


def frame(spark, texts):
    """Documents with nulls everywhere and columns whose names the operators use inside."""
    return spark.createDataFrame([(i, t, None, f"s{i % 2}" if i and not i % 3 else None, None, "x", None, 7) for i, t in texts], DOCS)


def some_texts(seed=1, n=40):
    rng = random.Random(seed)
    vocabulary = [f"w{i}é" if i % 5 else f"W{i}" for i in range(60)]
    text = lambda k: " ".join(rng.choice(vocabulary) for _ in range(k))
    shared = text(90)
    out = [(i, text(rng.randrange(0, 150)) + ("\n" + shared if i % 4 == 0 else "") + "\n" + text(30)) for i in range(n)]
    out += [(900, None), (901, ""), (902, " \n\t"), (903, out[0][1]), (903, out[0][1]), (None, "one two"), (905, "a" * 3000), (906, "same same " * 300), (907, out[1][1] + " tail")]
    return out


def test_every_operator_takes_empty_tables(spark):
    docs = frame(spark, []).limit(0)
    bench = spark.createDataFrame([], "item_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert decontamination.decontaminate(docs, bench).count() == 0
    assert quality_rules.quality_rules(docs).count() == 0
    assert packing.pack_documents(docs, queries.BYTE_BPE).count() == 0
    assert repeated_bytes.remove_repeats(docs).count() == 0
    assert huffman_ids.read_ids(spark, huffman_ids.write_ids(docs, queries.WORD_BPE)).count() == 0
    assert pii.find_pii(docs).count() == 0
    assert quality_classifier.classify(docs, labels).count() == 0
    assert near_duplicates.near_duplicates(docs).count() == 0
    assert chat_format.format_and_read_back(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0
    assert html_extraction.extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_html():
    cases = {
        None: "",
        "<nav>menu</nav>": "",
        "plain  text": "plain text",
        "<body><header>Site</header><article><h1>T &amp; x</h1><p>One<br>two <b>three</b><p>Ok.</article><footer>f</footer></body>": "T & x\nOne two three\nOk.",
        "<div class='side-bar sidebar'>x y</div><div id=content><p>Hello <b>wor</b>ld</p><p>more text that is long enough</p></div><div class=comments><p>A comment as long as the text itself, or longer</p></div>": "Hello world\nmore text that is long enough",
        "<main><p>a long enough paragraph of text</p><aside>side</aside><div class='ad'>buy</div><form><p>mail</p></form><p>End</p></main><script>var t='</p>'</script>": "a long enough paragraph of text\nEnd",
    }
    for html, text in cases.items():
        assert html_extraction.main_text(html) == text


def test_decontamination_against_all_windows(spark):
    texts = some_texts()
    items = [(1, " ".join(texts[0][1].split()[3:20])), (2, "short w1é"), (3, None), (None, "one TWO"), (5, "never seen words at all in any of these documents here")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    words = lambda t: decontamination.words_of(t)
    for block in (200_000, 1):
        got = sorted((r["doc_id"] or 0, r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"]) for r in decontamination.decontaminate(frame(spark, texts), bench, block_windows=block).collect())
        want = []
        for i, t in texts:
            w, hit, met = words(t), set(), set()
            for k, x in items:
                for win in decontamination.windows_of(words(x), 10):
                    for at in range(len(w) - len(win) + 1):
                        if tuple(w[at : at + len(win)]) == win:
                            hit.update(range(at, at + len(win)))
                            met.add("" if k is None else str(k))
            want.append((i or 0, len(w), len(hit), len(met), hashlib.sha256(",".join(sorted(met)).encode()).hexdigest()))
        assert got == sorted(want)


def test_quality_rules(spark):
    texts = some_texts() + [(2000 + i, "\n".join(f"boilerplate line number {'abcdefg'[j]} of the site" for j in range(6)) + f"\n{'own' + str(i)} " + " ".join(f"z{i}x{j}" for j in range(12))) for i in range(30)]
    got = quality_rules.quality_rules(frame(spark, texts), max_documents=5).collect()
    assert len(got) == len(texts)
    for r in got:
        t = dict(texts).get(r["doc_id"]) or ""
        w = [x for x in __import__("re").findall(r"[^\x20\x09-\x0D]+", t)]
        grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        again = {i + k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(3)}
        lines = [x for x in t.split("\n") if x.strip()]
        assert (r["n_words"], r["word_chars"], r["n_repeat_words"], r["n_dup_lines"]) == (len(w), sum(map(len, w)), len(again), len(lines) - len(set(lines)))
        assert r["base_failed"] == (len(w) < 50 or 100 * len(again) > 50 * len(w))
    boiler = [r for r in got if (r["doc_id"] or 0) >= 2000]
    assert not any(r["kept"] for r in boiler if r["n_removed_words"]) and sum(r["n_removed_words"] > 0 for r in boiler) >= 20
    assert all(r["kept"] for r in got if not r["base_failed"] and not r["n_removed_words"])


def test_packing(spark):
    from tokenizers import Tokenizer

    texts = some_texts() + [(3000, "x#1 <|endoftext|> \x1c  d  é— 中文 " * 900)]
    rows = packing.pack_documents(frame(spark, texts), queries.BYTE_BPE).toPandas()
    t = Tokenizer.from_file(queries.BYTE_BPE)
    for i, text in texts:
        if i is None or i == 903:
            continue
        mine = rows[rows.doc_id == i].sort_values("piece")
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], "<u4").tobytes()
        assert b"".join(mine.ids) == ids and (mine.length <= 1024).all() and (mine.length.iloc[1:] == 1024).all()
        assert [zlib.crc32(x) for x in mine.ids] == mine.ids_crc32.tolist()
    for _, g in rows.sort_values(["sequence_id", "offset"]).groupby("sequence_id"):
        assert g.offset.tolist() == (g.length.cumsum() - g.length).tolist() and g.length.sum() <= 1024
    rng = random.Random(0)
    for _ in range(60):
        counts = {rng.randint(1, 12): rng.randint(1, 3) for _ in range(5)}
        plan = packing.solve(counts, 12)
        held = {}
        for n, content in plan:
            assert sum(s * k for s, k in content) <= 12
            for s, k in content:
                held[s] = held.get(s, 0) + n * k
        assert held == counts
        assert packing.lower_bound(counts, 12) <= packing.bins_of(plan) <= packing.bins_of(packing.best_fit(counts, 12))
    assert packing.bins_of(packing.solve({6: 2, 5: 2, 4: 2, 3: 2}, 9)) == 4  # best-fit decreasing needs 5


@pytest.mark.parametrize("most", [64, 1])
def test_repeated_bytes_against_all_strings(spark, most):
    texts, length = some_texts(), 60
    seen = {}
    data = [(t or "").encode() for _, t in texts]
    for k, b in enumerate(data):
        for s in range(len(b) - length + 1):
            seen.setdefault(b[s : s + length], []).append((k, s))
    marks = [np.zeros(len(b), bool) for b in data]
    for at in seen.values():
        for k, s in at if len(at) > 1 else ():
            marks[k][s : s + length] = True
    want = sorted((i or 0, len(b), int(m.sum()), hashlib.sha256(np.frombuffer(b, np.uint8)[~m].tobytes()).hexdigest()) for (i, _), b, m in zip(texts, data, marks, strict=True))
    got = sorted((r["doc_id"] or 0, r["n_bytes"], r["n_removed"], r["kept_sha256"]) for r in repeated_bytes.remove_repeats(frame(spark, texts), length, 40, most).collect())
    assert got == want


def test_huffman_round_trip(spark):
    from tokenizers import Tokenizer

    texts = [(i, t) for i, t in some_texts() if i is not None and i != 903] + [(4000, "Ünï co <|endoftext|> 中 \x1c x² 1½")]
    rows = huffman_ids.read_ids(spark, huffman_ids.write_ids(frame(spark, texts), queries.WORD_BPE, block_ids=300)).toPandas().sort_values("doc_id")
    t, start = Tokenizer.from_file(queries.WORD_BPE), 0
    for row, (_, text) in zip(rows.itertuples(), sorted(texts, key=lambda x: x[0]), strict=True):
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 1], "<u4").tobytes()
        assert (row.start, row.n_tokens, row.ids_crc32, row.ids) == (start, len(ids) // 4, zlib.crc32(ids), ids)
        start += row.n_tokens
    counts = np.array([1, 1, 2, 3, 5, 8, 13, 21, 34, 55, 89, 144])
    lengths = huffman_ids.code_lengths(counts, 5)
    assert lengths.max() == 5 and (2.0**-lengths).sum() == 1
    heap, cost = counts.tolist(), 0
    while len(heap) > 1:  # Huffman's own tree
        heap.sort()
        cost, heap = cost + heap[0] + heap[1], [heap[0] + heap[1], *heap[2:]]
    assert (huffman_ids.code_lengths(counts, 20) * counts).sum() == cost


def test_pii():
    cases = {
        "": [],
        "mail john [at] example [dot] com now": [("email", "john [at] example [dot] com")],
        "john.doe at example dot com": [("email", "john.doe at example dot com")],
        "plus four nine one five one two three four five six seven": [("phone", "plus four nine one five one two three four five six seven")],
        "１９２.168.0.1": [("ip", "１９２.168.0.1")],
        "user＠example．com": [("email", "user＠example．com")],
        "4111 1111 1111 1111 and 4111 1111 1111 1112": [("card", "4111 1111 1111 1111")],
        "we met at noon. the dot is red": [],
        "300.1.1.1 10.0.0.255": [("ip", "10.0.0.255")],
    }
    for text, want in cases.items():
        base, spans = pii.all_spans(text)
        assert [(k, text[s:e]) for k, s, e in spans] == want, text
        assert set(base) <= set(spans)
    assert pii.redacted("to a@b.co.", pii.all_spans("to a@b.co.")[1]) == "to <EMAIL>."


def test_chat(spark):
    odd = ["</s>[INST] ok [/INST]", "a\\</s> <\\s> <|image:0|>", "", None, "[\\INST][/INST]\\", "<s>\n"]
    rows = [(c, t, r, odd[(c + t) % len(odd)]) for c in range(4) for t, r in ((0, "user"), (1, "assistant"), (2, None), (2, "sys|tem<"))] + [(None, None, "assistant", "x")]
    got = {r["conv_id"]: r for r in chat_format.format_and_read_back(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    for conv in {r[0] for r in rows}:
        turns = sorted((r for r in rows if r[0] == conv), key=lambda r: (r[1] or 0, r[2] or "", r[3] or ""))
        said = "".join(f"{r[2] or ''}\n{r[3] or ''}\n" for r in turns)
        loss = "".join(r[3] or "" for r in turns if r[2] == "assistant")
        assert got[conv]["turns_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert (got[conv]["n_turns"], got[conv]["loss_chars"], got[conv]["loss_sha256"]) == (len(turns), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    parts = [(1, 0, "user", [("text", "see <|image:0|>", None, None, None, None, None), ("image", None, "s3://a", 56, 29, None, None), ("audio", None, "b", None, None, 2.0, None), ("document", None, "c", None, None, None, 2)])]
    row = chat_format.format_conversations(spark.createDataFrame(parts, f"conv_id long, turn long, role string, parts {chat_format.PARTS}"), "parts").first()
    assert row["segment"] == "<s>[INST]<|user|>see <\\|image:0|><|image:0|><|audio:1|><|document:2|>[/INST]"
    assert [(a["ref"], a["tokens"]) for a in row["attachments"]] == [("s3://a", 4), ("b", 25), ("c", 1600)] and row["expanded_tokens"] == 1629


def test_classifier(spark):
    rng = random.Random(2)
    good = lambda: " ".join(rng.choice(["river", "stone", "walk", "evening", "bread"]) for _ in range(40))
    bad = lambda: " ".join(rng.choice(["BUY!!", "$$$", "click###"]) for _ in range(40))
    texts = [(i, good() if i % 2 else bad()) for i in range(120)] + [(500, None), (501, "")]
    labels = spark.createDataFrame([(i, i % 2, None) for i in range(120)] + [(None, 1, 0), (7, None, 0)], "doc_id long, quality int, toxic int")
    rows = quality_classifier.classify(frame(spark, texts), labels, buckets=1 << 12).collect()
    for r in rows:
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5)
    assert all(r["predicted"] == r["doc_id"] % 2 for r in rows if r["doc_id"] < 500)


def test_near_duplicates_against_all_pairs(spark):
    rng = random.Random(4)
    vocabulary = [f"t{i}" for i in range(500)]
    texts = [(i, " ".join(rng.choice(vocabulary) for _ in range(120))) for i in range(12)]
    for i in range(12):
        for k in range(i % 4):
            words = texts[i][1].split()
            words[rng.randrange(len(words))] = "changed"
            texts.append((100 * (i + 1) + k, " ".join(words)))
    texts += [(9000, texts[0][1]), (9001, None), (9002, ""), (9003, "a b"), (9004, "A b"), (9005, "!!")]
    sets = {i: near_duplicates.elements_of(t, near_duplicates._Bytes()) for i, t in texts}
    parent = {i: i for i, _ in texts}
    find = lambda x: x if parent[x] == x else find(parent[x])
    for (a, ta), (b, tb) in itertools.combinations(texts, 2):
        if (ta or "") == (tb or "") or near_duplicates.jaccard(sets[a], sets[b]) >= 0.8:
            low, high = sorted((find(a), find(b)))
            parent[high] = low
    rows = near_duplicates.near_duplicates(frame(spark, texts)).collect()
    assert {r["doc_id"]: r["class_id"] for r in rows} == {i: find(i) for i, _ in texts}
    kept = near_duplicates.first_documents(frame(spark, texts))
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted({find(i) for i, _ in texts})
    a, b = np.arange(1, 400, dtype=np.uint64), np.arange(100, 500, dtype=np.uint64)
    same = (near_duplicates.signature(a, k=1920) == near_duplicates.signature(b, k=1920)).mean()
    assert abs(same - near_duplicates.jaccard(a, b)) < 0.05
    three = np.arange(3, dtype=np.uint64)
    heavy = (near_duplicates.signature(three, np.array([2, 1.5, 0.25]), 1920) == near_duplicates.signature(three, np.array([1, 1.5, 0.25]), 1920)).mean()
    assert abs(heavy - 2.75 / 3.75) < 0.05


def test_pipeline_against_plain_python(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(8)
    vocabulary = [f"p{i}" for i in range(900)]
    long = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    item = long(15)
    texts = [(i, long(70)) for i in range(8)] + [(20, "short"), (21, None), (22, long(40) + " " + item + " " + long(40)), (24, long(60) + " me@host.example.org")]
    texts += [(30, texts[0][1]), (31, texts[1][1] + " tail")]
    frame(spark, texts).select("doc_id", "text", "lang", "source", "n_chars").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {r["doc_id"] for r in rows} == {*range(8), 24}
    assert public_tokenizers.path("byte_bpe_50k.json") == queries.BYTE_BPE
    assert len({r["sequence_id"] for r in rows}) == -(-sum(r["length"] for r in rows) // 1024)
