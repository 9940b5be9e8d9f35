"""Word hashing, tokenizing, packing, grammar, license scan, HTML: against plain Python and the library itself."""

import html
import random
import re
import time
import zlib
from collections import Counter

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from binlens.llm import decontaminate, html_text, license_scan, packing, repair, tokens, toxicity
from binlens.llm.common import text_buffers
from binlens.llm.queries import tokenizer
from binlens.llm.tokens import Encoder
from binlens.llm.words import ALNUM, SPACED, hash_of, windows, words

SF = "/root/testdata/sf0.001"
ODD = [None, "", " ", "a", "A b", "x" * 5000, "mit license MIT  License\nmit", "é é   z", "<|endoftext|> a <|endoftext|>", "\n\n a\n", "12 12 12", "word " * 400]


def lower(t):
    return re.sub("[A-Z]", lambda m: m.group().lower(), t or "")


def docs_of(spark, texts, ids=None):
    rows = [(i if ids is None else ids[k], t, "clash", 1.5) for k, (i, t) in enumerate(zip(range(len(texts)), texts))]
    return spark.createDataFrame(rows, "doc_id long, text string, n string, fp double")


def test_words_equal_regex():
    data, off = text_buffers(pa.array(ODD))
    w = words(data, off, SPACED)
    want = [re.findall(r"[^\x20\x09-\x0D]+", lower(t)) for t in ODD]
    assert list(w.counts) == [len(x) for x in want]
    assert [int(h) for h in w.hashes] == [hash_of(x) for r in want for x in r]
    assert len(windows(w.hashes, w.first, 5)[0]) == sum(max(0, len(r) - 4) for r in want)
    want = [re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t)) for t in ODD]
    w = words(data, off, ALNUM)
    assert [int(h) for h in w.hashes] == [hash_of(x, ALNUM) for r in want for x in r]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_encoder_equals_library(name):
    rnd = random.Random(5)
    parts = ["a", "B", "é", " ", "  ", "\n", "\t", "'s", "12", "!", " ", "日", "<|endoftext|>", "́", "Σ", "\r\n", "'", " ", "\x01", "%%%"]
    texts = ["".join(rnd.choice(parts) for _ in range(rnd.randint(0, 20))) for _ in range(4000)]
    texts += [r[0] for r in duckdb.sql(f"select text from '{SF}/documents.parquet'").fetchall()]
    e = Encoder(tokenizer(name))
    got = [f[b[i] : b[i + 1]].tolist() for _, f, b in e.encode(pa.array(texts), 0) for i in range(len(b) - 1)]
    assert got == [x.ids + [0] for x in e.library.encode_batch_fast(texts, add_special_tokens=False)]


@pytest.mark.parametrize("most", [5, 7, 21])
def test_encoder_grows_forgets_and_still_agrees(monkeypatch, most):
    monkeypatch.setattr(tokens, "SLOTS", 5)
    monkeypatch.setattr(tokens, "MOST_SLOTS", most)
    e = Encoder(tokenizer("byte_bpe_50k.json"))
    texts = [f"w{i} x{i % 7} common" for i in range(100)] + [" ".join(f"y{i}" for i in range(300)), "common w5"]
    got = [f[b[i] : b[i + 1]].tolist() for _, f, b in e.encode(pa.array(texts), None, 200) for i in range(len(b) - 1)]
    assert got == [x.ids for x in e.library.encode_batch_fast(texts, add_special_tokens=False)]


def library_ids(texts, name, end):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer(name))
    return [t.encode(x or "", add_special_tokens=False).ids + [end] for x in texts]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_packing_brute_force(spark):
    texts = ODD + ["word " * 5000]
    want = dict(enumerate(library_ids(texts, "word_bpe_49k.json", 1)))
    rows = packing.pack(docs_of(spark, texts), tokenizer("word_bpe_49k.json")).collect()
    assert len({r.sequence_id for r in rows}) == len(rows) and all(r.offset == 0 for r in rows)
    pieces = {}
    for r in sorted(rows, key=lambda r: (r.doc_id, r.start)):
        ids = want[r.doc_id]
        assert r.doc_tokens == len(ids) and r.start == pieces.get(r.doc_id, 0)
        assert r.length == 1 << r.bucket and r.length <= 2048 and r.ids_crc32 == crc(ids[r.start : r.start + r.length])
        pieces[r.doc_id] = r.start + r.length
    assert pieces == {d: len(x) for d, x in want.items()}
    assert packing.pack(docs_of(spark, []), tokenizer("word_bpe_49k.json")).count() == 0
    with_ids = packing.pack(docs_of(spark, ["a b"]), tokenizer("word_bpe_49k.json"), with_ids=True).collect()
    assert sum((r.ids for r in with_ids), []) == library_ids(["a b"], "word_bpe_49k.json", 1)[0]
    assert sum(r.n_ids for r in packing.buckets(packing.pack(docs_of(spark, texts), tokenizer("word_bpe_49k.json"))).collect()) == sum(map(len, want.values()))


def test_grammar_round_trip_and_access():
    rnd = random.Random(1)
    for _ in range(150):
        x = np.array([rnd.randint(0, rnd.choice([1, 3, 30])) for _ in range(rnd.randint(1, 400))], np.uint32)
        g = repair.compress(x, least=2)
        assert (g.expand(g.sequence) == x).all()
        a = rnd.randrange(len(x))
        b = rnd.randint(a + 1, len(x))
        assert (g.decode(a, b) == x[a:b]).all()
    g = repair.compress(np.zeros(10_000, np.uint32))
    assert len(g.sequence) + 2 * len(g.left) < 60


def test_grammar_leaves_no_pair_that_pays():
    rnd = np.random.default_rng(2)
    for per_round in (3, 4096):
        x = np.concatenate([rnd.zipf(1.3, 20_000) % 500, np.tile(rnd.integers(0, 500, 700), 12)]).astype(np.uint32)
        g = repair.compress(x, per_round=per_round)
        pairs = Counter(zip(g.sequence[:-1].tolist(), g.sequence[1:].tolist()))
        assert max(pairs.values()) < 4 and (g.expand(g.sequence) == x).all()


def test_grammar_keeps_null_and_repeated_ids(spark, tmp_path):
    texts = ["no id", "minus one", "first of seven " * 300, "second of seven " * 300, "third of seven " * 300, "eight", "no id either"]
    docs = docs_of(spark, texts, [None, -1, 7, 7, 7, 8, None])
    rows = sorted(repair.round_trip(docs, tokenizer("byte_bpe_50k.json"), shard_ids=400).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in rows] == [None, None, -1, 7, 7, 7, 8]
    path = str(tmp_path / "shards")
    repair.write_shards(docs, path, tokenizer("byte_bpe_50k.json"), shard_ids=400)
    shards = repair.read_shards(spark, path)
    got, flat = repair.document(shards, 7), []
    while got:  # ids of the documents, each closed by 0
        flat.append(got[: got.index(0) + 1])
        got = got[got.index(0) + 1 :]
    assert sorted(flat) == sorted(library_ids(texts[2:5], "byte_bpe_50k.json", 0))
    assert repair.document(shards, -1) == library_ids(["minus one"], "byte_bpe_50k.json", 0)[0] and repair.document(shards, 0) == []


def test_grammar_files(spark, tmp_path):
    texts = ODD + ["word " * 3000, "a"]
    ids = list(range(len(texts) - 1)) + [3]  # one id twice
    want = sorted(zip(ids, library_ids(texts, "byte_bpe_50k.json", 0)), key=lambda x: x[0])
    docs = docs_of(spark, texts, ids)
    rows = sorted(repair.round_trip(docs, tokenizer("byte_bpe_50k.json"), shard_ids=500).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in rows] == [d for d, _ in want]
    assert sorted((r.doc_id, r.n_tokens, r.ids_crc32) for r in rows) == sorted((d, len(x), crc(x)) for d, x in want)
    at = 0
    for r in rows:
        assert r.start == at
        at += r.n_tokens
    path = str(tmp_path / "shards")
    repair.write_shards(docs, path, tokenizer("byte_bpe_50k.json"), shard_ids=500)
    shards = repair.read_shards(spark, path)
    assert repair.document(shards, len(texts) - 2) == dict(want)[len(texts) - 2]
    assert repair.round_trip(docs_of(spark, []), tokenizer("byte_bpe_50k.json")).count() == 0


def test_license_base_brute_force(spark):
    texts = ODD + ["This is MIT license; Apache License, and the GNU General Public License.", "mit-license apache\nlicense",
        "released under the MIT license.", "Licensed under the Apache License, Version 2.0.", "licensed under CC BY-NC 4.0."]
    rows = {r.doc_id: r for r in license_scan.scan(docs_of(spark, texts)).collect()}
    for i, t in enumerate(texts):
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
        at = [(k, label) for phrase, label in license_scan.BASE for k in range(len(w)) if w[k : k + len(phrase.split())] == phrase.split()]
        r = rows[i]
        assert (r.n_words, r.n_base) == (len(w), len(at))
        assert (r.first_word, r.last_word) == ((min(at)[0], max(at)[0]) if at else (None, None))
        assert r.base_labels == ",".join(sorted({x for _, x in at}))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1
    assert "mit-notice" in rows[len(ODD) + 2].labels and "apache-2.0" in rows[len(ODD) + 3].labels
    assert rows[len(ODD) + 4].labels == "cc-by-nc-4.0" and rows[0].labels == ""
    assert license_scan.scan(docs_of(spark, [])).count() == 0


def test_license_alignment_is_positional():
    index = license_scan.template_index()
    index.idf = np.ones(len(index.vocabulary))
    h = lambda t: np.array([hash_of(x, ALNUM) for x in t.split()], np.uint64)
    assert "bsd" in license_scan.align(h("x y redistribution and use in source and binary forms with or without changes are allowed"), index)
    assert "bsd" not in license_scan.align(h("forms binary source use redistribution permitted modification"), index)


def test_license_notices_do_not_displace_each_other(spark):
    notice = {label: text for label, text, _ in license_scan.TEMPLATES}
    pairs = [("isc", "cc-by-4.0"), ("mit-text", "apache-2.0"), ("bsd", "mit-notice"), ("unlicense", "lgpl")]
    prose = " hereby granted obtaining redistribution modification unencumbered person charge copy documentation "
    texts = [notice[a] + prose + notice[b] for a, b in pairs] + [" and ".join(notice.values())]
    got = [set(r.labels.split(",")) for r in license_scan.scan(docs_of(spark, texts)).orderBy("doc_id").collect()]
    assert all(set(p) <= g for p, g in zip(pairs, got)) and set(notice) <= got[-1]


def brute_licences(text, votes=2, slack=2):
    """Labels by trying every start of every template in plain Python, without anchors or hashes."""
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))
    at = lambda start, words_: 0 <= start and w[start : start + len(words_)] == words_
    out = {label for phrase, label in license_scan.BASE if any(at(k, phrase.split()) for k in range(len(w)))}
    for label, notice, must in license_scan.TEMPLATES:
        parts = notice.split()
        place = {m: next(q for q in range(len(parts)) if parts[q : q + len(m.split())] == m.split()) for m in must}
        for start in range(-len(parts), len(w)):
            if all(any(at(start + place[m] + d, m.split()) for d in range(-slack, slack + 1)) for m in must):
                same = {p for q, p in enumerate(parts) if 0 <= start + q < len(w) and w[start + q] == p}
                if len(same) >= min(votes, len(set(parts))):
                    out.add(label)
    return out


def test_license_labels_brute_force(spark):
    rnd = random.Random(6)
    vocabulary = sorted({x for _, t, _ in license_scan.TEMPLATES for x in t.split()}) + ["x", "y"]
    texts = [None, ""]
    for _ in range(120):
        words_ = [rnd.choice(vocabulary) for _ in range(rnd.randint(0, 60))]
        for _, notice, must in rnd.sample(license_scan.TEMPLATES, rnd.randint(0, 3)):
            part = [x for x in rnd.choice([notice, *must]).split() if rnd.random() > 0.04]
            k = rnd.randint(0, len(words_))
            words_[k:k] = part
        texts.append(rnd.choice([" ", ", ", "\n"]).join(words_))
    rows = {r.doc_id: r for r in license_scan.scan(docs_of(spark, texts)).collect()}
    assert any(rows[k].labels for k in rows)
    for k, t in enumerate(texts):
        assert set(filter(None, rows[k].labels.split(","))) == brute_licences(t)
        assert rows[k].score == (1.0 if rows[k].base_labels else rows[k].score) and (rows[k].score > 0) == bool(rows[k].labels)


def test_html_equals_article(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    got = {r.page_id: r for r in html_text.extract(pages).collect()}
    for r in pages.collect():
        article = re.search(r"<article>(.*?)</article>", r.html, re.S)
        parts = re.split(r"</?(?:h1|p)>", article[1])
        want = "\n".join(filter(None, (" ".join(html.unescape(re.sub(r"<br>", " ", p).replace("<b>", "").replace("</b>", "")).split()) for p in parts)))
        assert got[r.page_id].text == want and got[r.page_id].n_chars == len(want)


def test_html_edge_cases(spark):
    cases = {
        "<main><p>Yes, this is the &amp; text of it.</p><aside>no</aside><div id=comments><p>bad comment of the user</p></div></main>": "Yes, this is the & text of it.",
        "<body><nav><a href=x>Home</a></nav><p>" + "the story of a man that was in the wood " * 5 + "</p><p>Short.</p><footer>c 2020</footer></body>": ("the story of a man that was in the wood " * 5).strip() + "\nShort.",
            
        "<article><p>one<p>two &lt;b&gt;<script>var a='<p>no</p>'</script></article>": "one\ntwo <b>",
        "<article><p>open": "open", "": "", "<": "<" if False else html_text.main_text("<"), "<div class='ad'>buy</div>": "",
    }
    for page, want in cases.items():
        assert html_text.main_text(page) == want
    frame = spark.createDataFrame([(1, None, None), (1, "u", "<article>x</article>"), (1, "u", "<article>x</article>")], "page_id long, url string, html string")
    assert sorted((r.page_id, r.text, r.n_chars) for r in html_text.extract(frame).collect()) == [(1, "", 0), (1, "x", 1), (1, "x", 1)]
    assert html_text.extract(frame.limit(0)).count() == 0


def test_html_both_passes_decide():
    """Pages without an article element, and articles whose blocks the text rules decide."""
    long = "the story of a man that was in the wood and of all that he had to do there"
    menu = "".join(f"<li><a href=/{k}>entry number {k}</a></li>" for k in range(6))
    page = f"<body class='single has-sidebar no-comments'><ul>{menu}</ul><h1>The head</h1><p>{long}.</p><p>Yes!</p><p>{long}?</p><div class=left-sidebar>{long}</div><p>{'<a href=x>more to read of this kind</a> ' * 4}</p><p>all rights</p><ul>{menu}</ul></body>"
    assert html_text.main_text(page) == f"The head\n{long}.\nYes!\n{long}?"
    why = [(text.split(" ")[0], keep, by) for (text, *_), (keep, by) in zip(html_text.blocks(page), html_text.decide(html_text.blocks(page)))]
    assert ("Yes!", True, "neighbours") in why and ("all", False, "neighbours") in why and Counter(by for *_, by in why) == {"links": 13, "text": 2,
        "neighbours": 3, "structure": 1}
    inside = f"<article><h2>Zzqx</h2><p>{long}</p><p>qqq www</p><p>{'<a href=x>more to read of this kind</a> ' * 4}</p><p>{'zzx qqv ' * 20}</p></article><p>{long}</p>"
    assert [by for _, by in html_text.decide(html_text.blocks(inside))] == ["neighbours", "text", "neighbours", "links", "neighbours", "structure"]
    assert [by for _, by in html_text.decide(html_text.blocks("<article><p>one</p></article>"))] == ["alone"]


def test_html_ties_go_to_the_block_before():
    long = "the of and to in a is that for it as was with be by on not he his but at are"
    rows = [("x", 1.0, False, False, False), ("short", 0.0, False, False, False), (long, 0.0, False, False, False)]
    assert html_text.decide(rows)[1] == (False, "neighbours") and html_text.decide(rows[::-1])[1] == (True, "neighbours")
    rows[1] = ("Head", 0.0, False, False, True)
    assert html_text.decide(rows)[1] == (True, "neighbours") and html_text.decide(rows[::-1])[1] == (False, "neighbours")


@pytest.mark.parametrize("part", ["<a ", "<div>", "<p>ab", '<a href="', "<b 'x", "<li>no", "</p>", "<!-", "&amp"])
def test_html_takes_linear_time(part):
    def spent(n):
        began = time.process_time()
        html_text.main_text(part * n)
        return time.process_time() - began

    spent(2_000)
    assert spent(100_000) < 40 * max(spent(10_000), 0.02)


def test_html_ignores_clashing_columns(spark):
    frame = spark.createDataFrame([(1, "u", "<p>x</p>", "t", 5)], "page_id long, url string, html string, text string, n_chars int")
    assert [tuple(r) for r in html_text.extract(frame).collect()] == [(1, "u", "", 0)]


ITEM = "A train leaves Boston at 9 and travels 60 km in 2 hours while Anna walks 4 km to the same old station near the river"


def test_decontamination_templates(spark):
    changed = ITEM.replace("60", "75").replace("Anna", "Maria").replace("Boston", "Denver").replace("9", "7")
    bench = spark.createDataFrame([(1, ITEM, 0), (2, None, 0), (3, "", 0), (4, "four words are here", 0)], "item_id long, text string, doc_id int")
    texts = ["x " * 30 + ITEM + " y" * 20, "so: " + changed, ITEM.upper(), ITEM.replace("4 km", "60 km").replace("60 km in", "50 km in").replace("4",
        "5"), "nothing of the kind " * 20, None, ""]
    rows = {(r.doc_id, r.item_id): r for r in decontaminate.contaminated(docs_of(spark, texts), bench).collect()}
    assert {k for k in rows if k[1] == 1} >= {(0, 1), (1, 1), (2, 1)} and not any(d in (4, 5, 6) for d, _ in rows)
    assert rows[1, 1].reparameterised and not rows[0, 1].reparameterised and rows[0, 1].coverage == 1.0 and rows[0, 1].first_word == 30
    kept = decontaminate.keep_clean(docs_of(spark, texts), bench)
    assert kept.columns == ["doc_id", "text", "n", "fp"] and {4, 5, 6} <= {r.doc_id for r in kept.collect()} and not {0, 1, 2} & {r.doc_id for r in kept.collect()}
    assert decontaminate.contaminated(docs_of(spark, []), bench).count() == 0 and decontaminate.contaminated(docs_of(spark, texts), bench.limit(0)).count() == 0


def test_decontamination_slots_must_agree(spark):
    item = "take 3 apples from the basket and put 3 apples in the box then count the 3 apples again with care"
    good, bad = item.replace("3", "8"), item.replace("3", "8", 1).replace("3", "5")
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert {r.doc_id for r in decontaminate.contaminated(docs_of(spark, [good, bad]), bench).collect()} == {0}


def found_in(spark, items, texts):
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    return {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs_of(spark, texts), bench).collect()}


def test_decontamination_slots_of_other_lengths(spark):
    short = "How far is it when Anna walks 60 km and then goes home again slowly"
    dense = "12 of 30 and 7 of 15 and 4 of 9 and 2"
    items = [ITEM, short, dense, "add 4 and 5 now", "12 13 14 15 16"]
    texts = [
        ITEM.replace("60", "62.5").replace("Anna", "Mary Ann"), ITEM.replace("60", "1,200").replace("Boston", "New York"), "so " + short.replace("60",
            "62.5").replace("Anna", "Mary Ann"),
        "x y " + ITEM.replace("walks", "walks for about three more") + " z", "here: " + dense, "now add 4 and 5 now", "see 12 13 14 15 16", "see 12 13 14 15 17",
    ]
    assert found_in(spark, items, texts) == {(0, 0), (1, 0), (2, 1), (3, 0), (4, 2), (5, 3), (6, 4)}
    assert found_in(spark, [texts[0]], [ITEM, texts[0].lower()]) == {(0, 0), (1, 0)}


def test_decontamination_finds_short_items_as_whole_documents(spark):
    items = ["42", "why not", "7 of 9", "a b c d", "12 30", "km"]
    texts = ["42", "the 42", "Why not?", "so why not now", "7 of 9.", "x a b c d y", "12 30", "km", None, ""]
    assert found_in(spark, items, texts) == {(0, 0), (2, 1), (4, 2), (5, 3), (6, 4), (7, 5)}


def test_decontamination_by_several_blocks(spark, monkeypatch):
    docs = docs_of(spark, [ITEM, "clean text of some words", "why not", None, "x " * 50_000 + ITEM])
    bench = spark.createDataFrame([(0, ITEM), (1, "why not")], "item_id long, text string")
    monkeypatch.setattr(decontaminate, "benchmark_blocks", lambda b: iter([decontaminate.items_of([r.item_id], [r.text]) for r in b.collect()]))
    assert sorted(r.doc_id for r in decontaminate.keep_clean(docs, bench).collect()) == [1, 3]
    assert decontaminate.keep_clean(docs, bench).columns == docs.columns


def test_decontamination_keeps_what_agrees(spark):
    middle = "then she counts all of the ripe apples that were lying under the old tree behind the house and writes the total down"
    item = f"take 3 apples first {middle} and add 3 apples to them and 3 more"
    texts = [item.replace("3", "8", 1), item.replace("3", "8", 1).replace("add 3", "add 5"), "take 3 apples first and add 4 apples to them"]
    assert found_in(spark, [item], texts) == {(0, 0), (1, 0)}


def test_decontamination_finds_planted(spark):
    docs, bench = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    got = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, bench).collect()}
    want = {(d.doc_id, b.item_id) for d in docs.collect() for b in bench.collect() if b.text in d.text}
    assert want <= got and {d for d, _ in got} == {d for d, _ in want}


def test_toxicity_held_out(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    model = toxicity.fit(docs, labels.where("pmod(xxhash64(doc_id, 7), 3) > 0"))
    assert (np.diff(model.cuts) > 0).all()
    rows = toxicity.score(docs, model).join(labels.where("pmod(xxhash64(doc_id, 7), 3) = 0"), "doc_id").collect()
    caught = np.mean([r.rejected for r in rows if r.toxic])
    wrong = np.mean([r.rejected for r in rows if not r.toxic])
    assert caught >= 0.85 and wrong <= 0.005  # about one label in twenty of this table names no word at all
    assert {r.grade for r in rows} == {0, 1, 2} and all(0 <= r.severity <= 2 and r.severity >= r.p_toxic - 1e-9 for r in rows)


def test_toxicity_fit_is_at_its_optimum():
    """The penalised likelihood's optimality conditions, computed anew from the definition."""
    rnd = np.random.default_rng(5)
    toxic = (rnd.random(900) < 0.3).astype(np.int64)
    rows = [np.unique(np.concatenate([rnd.integers(0, 200, 12), rnd.integers(1000, 1010, 2 * t), rnd.integers(1000, 1010, int(rnd.random() < 0.05))])) for t in toxic]
    buckets, bounds = np.concatenate(rows).astype(np.int32), np.concatenate([[0], np.cumsum([len(r) for r in rows])])
    ridge, lasso, balance = 1e-3, 1e-3, 0.7
    m = toxicity.fit_ordinal(buckets, bounds, toxic, rounds=4000, ridge=ridge, lasso=lasso, balance=balance)
    used, col, row = toxicity.screened(buckets, bounds, toxic)
    grade = toxicity.grades(col, row, toxic, len(used))
    x = np.zeros((900, len(used)))
    x[row, col] = 1
    bad = toxic > 0
    weight = np.where(bad, (0.5 / bad.mean()) ** balance, (0.5 / (~bad).mean()) ** balance) / 900
    w = m.weights[used].astype(float)
    p = 1 / (1 + np.exp(-(x @ w)[:, None] + m.cuts[None, :]))
    slack = (p - (grade[:, None] > np.arange(len(m.cuts))[None, :])) * weight[:, None]
    grad = x.T @ slack.sum(axis=1) + ridge * w
    assert len(used) and (np.abs(grad) <= lasso + 2e-4).all() and np.abs(grad + lasso * np.sign(w))[w != 0].max() < 2e-4
    assert np.abs(slack.sum(axis=0)).max() < 1e-3 and (np.diff(m.cuts) > 0).all()


def test_toxicity_fit_is_bounded(spark):
    texts = [f"word{k} idiot scum" for k in range(300)] + ["many " + " ".join(f"w{chr(97 + a)}{chr(97 + b)}" for a in range(26) for b in range(26))]
    docs = docs_of(spark, texts, [5] * 300 + [6])
    labels = spark.createDataFrame([(5, 1), (5, 0), (6, 1)], "doc_id long, toxic int")
    col, bounds, y = toxicity.training_rows(docs, labels, max_labelled=1)
    assert len(y) <= 1 and len(bounds) == len(y) + 1
    assert len(toxicity.training_rows(docs, labels)[2]) == 2 and len(toxicity.training_rows(docs, labels, max_words=100)[2]) == 1


def test_toxicity_scores_whole_long_texts(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = toxicity.fit(docs, labels)
    bad = docs.join(toxicity.score(docs, model).orderBy("severity", ascending=False).limit(1), "doc_id").first().text
    rows = toxicity.score(docs_of(spark, ["plain " * 300_000 + bad, bad]), model).collect()
    assert rows[0].severity == pytest.approx(rows[1].severity) and rows[0].rejected


def test_toxicity_edge_cases(spark):
    docs = docs_of(spark, ODD)
    labels = spark.createDataFrame([(1, 0, None), (2, None, 1), (None, 1, 1)], "doc_id long, toxic int, quality int")
    model = toxicity.fit(docs, labels)
    assert toxicity.score(docs, model).where("rejected").count() == 0
    assert toxicity.fit(docs_of(spark, []), labels).weights.any() == False  # noqa: E712
    kept = toxicity.keep_clean(docs, model)
    assert kept.columns == docs.columns and kept.count() == len(ODD)
