"""BPE, token counts, decontamination, language, HTML and licence notices on small and awkward inputs."""

import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken

from approxdq.llm import bpe, decontaminate, htmltext, langid, licenses, tokencounts

PATH = P.path("byte_bpe_multi_50k.tiktoken")
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
TEXTS = ["", None, "a", "Hello  world\n\n\n it's 2024!!", "é" * 300, " " * 500 + "x", "a" * 3000, "漢字かな交じり文 \U0001f600\U0001f600", "line one\nline two\r\n\ttab", "word " * 400, "\x00\x01 control", "ﬀ ligature ß ẞ"]


def frame(spark, texts, **extra):
    return spark.createDataFrame([(i, t, "clash") for i, t in enumerate(texts)], "doc_id long, text string, ids string")


def test_bpe_equals_the_public_library(spark):
    enc = bpe.encoder(PATH, P.PATTERN)
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=enc.rank, special_tokens={})
    r = random.Random(0)
    texts = TEXTS + ["".join(r.choice(" \n\té123ßzZ!$漢 the ing") for _ in range(60)) for _ in range(300)]
    for got in bpe.encode_documents(frame(spark, texts), PATH, P.PATTERN, ids=True).collect():
        want = ref.encode_ordinary(texts[got.doc_id] or "")
        assert list(got.ids) == want and got.n_tokens == len(want) and got.same_bytes
        assert got.ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
        assert got.decoded_sha256 == hashlib.sha256((texts[got.doc_id] or "").encode()).hexdigest()


def test_cache_bound_changes_nothing(monkeypatch):
    monkeypatch.setattr(bpe, "REMEMBER", 4)
    monkeypatch.setattr(bpe, "KEEP", 2)
    small, big = bpe.ByteEncoder(PATH, P.PATTERN), bpe.encoder(PATH, P.PATTERN)
    for t in TEXTS:
        assert small.encode(t or "") == big.encode(t or "")


@pytest.mark.parametrize("rule", tokencounts.RULES)
def test_token_counts_add_up(spark, rule):
    enc = bpe.encoder(PATH, P.PATTERN)
    rows = tokencounts.tokens_by_section(frame(spark, TEXTS), PATH, P.PATTERN, rule).collect()
    by = {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
    for i, t in enumerate(TEXTS):
        own = sorted(by[i], key=lambda r: r.section)
        assert abs(sum(r.n_tokens for r in own) - len(enc.encode(t or ""))) < 1e-9
        assert own[0].char_start == 0 and own[-1].char_end == len(t or "") and all(a.char_end == b.char_start for a, b in zip(own, own[1:]))


def test_boundary_rules():
    starts, ends, borders = np.array([0, 2, 5]), np.array([2, 5, 6]), np.array([3, 6])
    assert list(tokencounts.attribute(starts, ends, borders, "first")[0]) == [2, 1]
    assert list(tokencounts.attribute(starts, ends, borders, "most")[0]) == [1, 2]
    assert np.allclose(tokencounts.attribute(starts, ends, borders, "split")[0], [4 / 3, 5 / 3])
    assert list(tokencounts.attribute(starts, ends, borders, "first")[1]) == [1, 0]


def brute_hits(text, items, n=10):
    words = WORD.findall((text or "").translate({c: c + 32 for c in range(65, 91)}))
    hit, found = set(), set()
    for item, t in items:
        own = WORD.findall((t or "").translate({c: c + 32 for c in range(65, 91)}))
        size = min(n, len(own))
        grams = {tuple(own[i : i + size]) for i in range(len(own) - size + 1)} if own else set()
        for i in range(len(words) - size + 1):
            if tuple(words[i : i + size]) in grams:
                hit |= set(range(i, i + size))
                found.add(str(item))
    return len(words), len(hit), sorted(found)


@pytest.mark.parametrize("most_bytes", [1 << 20, 40])
def test_decontamination_against_brute_force(spark, most_bytes):
    r = random.Random(1)
    vocab = ["a", "b", "Cé", "d1", "e"]
    items = [(i, " ".join(r.choice(vocab) for _ in range(k))) for i, k in enumerate([12, 12, 10, 3, 1])] + [(9, None), (10, ""), (11, "short zz item"), (11, "short zz item")]
    texts = [", ".join(r.choice(vocab[:4]) for _ in range(60)) for _ in range(30)] + [items[0][1].upper() + "!", None, "", "x SHORT... zz item y"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    docs = frame(spark, texts)
    for got in decontaminate.contamination(docs, bench, most_bytes=most_bytes).collect():
        n, hit, found = brute_hits(texts[got.doc_id], items)
        assert (got.n_words, got.n_hit, list(got["items"])) == (n, hit, found) and got.contaminated == (hit > 0)
        assert got.items_sha256 == hashlib.sha256(",".join(found).encode()).hexdigest()
    own = bench.where("item_id = 11")
    kept = decontaminate.clean_documents(docs, own)
    assert kept.columns == docs.columns and len(texts) - 1 not in {r.doc_id for r in kept.collect()}
    cut = {r.doc_id: r.text for r in decontaminate.clean_documents(docs, own, remove="spans").collect()}
    assert cut[len(texts) - 1] == "x  y" and cut[0] == texts[0] and cut[len(texts) - 3] is None
    assert decontaminate.contamination(docs, bench.where("false")).where("contaminated").count() == 0


def test_gradients_by_differences():
    net = langid.ByteGRU(["a", "b", "c"], 3)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    r = np.random.default_rng(0)
    x, y, w = r.integers(0, 5, (4, 6)).astype(np.uint8), np.array([0, 1, 2, 1]), np.ones((4, 6))
    w[0, 4:] = 0
    _, grads = net.gradients(x, y, w)
    for name, p in net.p.items():
        for _ in range(6):
            at = tuple(r.integers(0, s) for s in p.shape)
            old, side = p[at], []
            for e in (1e-3, -1e-3):
                p[at] = old + e
                side.append(net.gradients(x, y, w)[0])
            p[at] = old
            assert abs((side[0] - side[1]) / 2e-3 - grads[name][at]) < 2e-3


def test_language_held_out_accuracy_and_und(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    lang = {r.doc_id: r.lang for r in docs.collect()}
    got = langid.identified(docs).collect()
    assert len(got) == len(lang) and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 for r in got)
    held = [r.lang_pred == lang[r.doc_id] for r in got if r.held_out]
    assert sum(held) / len(held) > 0.95
    odd = spark.createDataFrame([(1, None, "en"), (2, "", "en"), (3, "12 ;; 4", "de"), (4, "the house of the river", None), (5, "und der Weg ist nicht weit", "de")], "doc_id long, text string, lang string")
    pred = {r.doc_id: r for r in langid.identified(odd).collect()}
    assert all(pred[i].lang_pred == "und" and pred[i].score == 0 for i in (1, 2, 3)) and pred[4].lang_pred in ("de", "und")
    assert {r.lang_pred for r in langid.identified(odd.withColumn("lang", __import__("pyspark").sql.functions.lit(None).cast("string"))).collect()} == {"und"}
    assert langid.accepted(odd.where("false")).count() == 0


def test_long_and_segmented_texts_are_whole():
    net = langid.ByteGRU(["a", "b"])
    body = b"x" * 1000 + b"yz" * 333
    data = np.frombuffer(body * 2, np.uint8)
    pooled = net.pooled(data, np.array([0, len(body), len(body), 2 * len(body)]))
    assert np.allclose(pooled[0], pooled[2]) and np.allclose(pooled[0].sum(), 1) and np.allclose(pooled[1], 0)


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><nav><ul><li>Menu</ul></nav>
<div class="ad">Buy</div><article><h1>Head &amp; more</h1><p>One  two<br>three<p><b>Bold<p>Last&nbsp;one %s</p><div class="share">Share us</div><div><p>Own box</p></div><section class="comments"><p>First!</p></section></article><footer>&copy; x</footer></body></html>"""


def test_main_text():
    assert htmltext.main_text(PAGE % "é") == "Head & more\nOne two three\nBold\nLast one é\nOwn box"
    assert htmltext.main_text("") == "" and htmltext.main_text("plain &lt; text") == "plain < text"
    assert htmltext.main_text("<div>a<table><tr><td>x<td>y</table></div>b") == "a\nx\ny\nb"
    assert htmltext.main_text("<p>" * 3000 + "deep" + "<div>" * 3000 + "x") == "deep\nx"


def test_templates_of_a_host_go(spark):
    body = "<html><body><div><span>Site banner text</span></div><div><p>Own words %d</p></div></body></html>"
    rows = [(i, f"https://h.example.com/{i}", body % i) for i in range(8)] + [(100, "https://other.example.com/", body % 100), (101, None, body % 101), (102, "https://h.example.com/e", None), (103, "https://h.example.com/f", "")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text for r in htmltext.main_texts(pages).collect()}
    assert all(got[i] == f"Own words {i}" for i in range(8))
    assert got[100] == "Site banner text\nOwn words 100" and got[101] == "Site banner text\nOwn words 101" and got[102] == got[103] == ""
    assert htmltext.main_texts(pages.where("false")).count() == 0


def test_nothing_in_an_article_or_main_goes_by_hash(spark):
    inner = "<b>Same lead</b><span>Same note</span><p>Own %d</p><ul><li>Same item</li></ul><div><section>Same box</section></div><table><tr><td>Same cell</td></tr></table>"
    whole = "Same lead Same note\nOwn {0}\nSame item\nSame box\nSame cell".replace("lead Same", "leadSame")
    bodies = {0: "<div>Site line</div><article>%s</article>" % inner, 100: "<div>Site line</div><main>%s</main>" % inner, 200: "<div><div>Site line</div><div>Bare %d</div></div>"}
    rows = [(i, f"https://h.example.com/{i}", b % i) for at, b in bodies.items() for i in range(at, at + 8)]
    got = {r.page_id: r.text for r in htmltext.main_texts(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == (whole.format(i) if i < 200 else f"Bare {i}") for i, _, _ in rows)


def test_copies_of_a_page_make_no_templates(spark):
    page = "<script>track(%d)</script><div>Lead of %s</div><div><p>Body of %s</p></div>"
    rows = [(i, f"https://h.example.com/{i}", page % (i, "A" if i < 8 else i, "A" if i < 8 else i)) for i in range(20)]
    rows += [(i, f"https://all.example.com/{i}", page % (i, "B", "B")) for i in range(20, 40)]
    got = {r.page_id: r.text for r in htmltext.main_texts(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == f"Lead of {x}\nBody of {x}" for i in range(40) for x in ["A" if i < 8 else i if i < 20 else "B"])


def test_license_notices(spark):
    texts = ["Released under the MIT License. under the mit license", "under teh MIT licence", "Licensed: CC-BY-NC", "Apache License, Version 2.0", "Permission is hereby granted, free of charge, to any person obtaining a copi", None, "", "cc by ncx", "under the mitlicense"]
    got = {r.doc_id: r for r in licenses.license_notices(frame(spark, texts)).collect()}
    assert (got[0].n_base, got[0].first_word, got[0].last_word, got[0].base_labels, got[0].score) == (2, 1, 5, "mit", 1.0)
    assert (got[1].n_base, got[1].first_word, got[1].base_labels) == (0, None, "") and got[2].base_labels == "cc-by-nc" and got[3].n_base == 1
    assert got[4].labels == "mit" and 0.9 < got[4].score < 1 and got[5].n_words == got[6].n_words == 0 and got[7].n_base == 0


def test_seeds_lose_no_notice():
    import regex

    search, r = licenses.NoticeSearch(), random.Random(0)
    for notice, label in licenses.NOTICES:
        e = licenses.edits_for(notice)
        for _ in range(20):
            t = list(notice)
            for _ in range(e):
                t[r.randrange(len(t))] = r.choice("xyz")
            text = "aa " + "".join(t) + " bb"
            whole = regex.search(rf"(?e)(?<![^ ])(?:{regex.escape(notice, literal_spaces=True)}){{e<={e}}}(?![^ ])", text)
            assert (whole is None) or any(s[2] == label for s in search.spans(text))
