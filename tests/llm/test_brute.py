"""Queries without SQL twins against plain Python, on whole small tables and awkward fixtures."""

import re
import time

import public_tokenizers as P
import pytest
from test_text import PATH, TEXTS, brute_hits, frame

from approxdq.llm import bpe, decontaminate, htmltext, licenses, queries, tokencounts

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def plain_sections(text, enc, rule):
    """Token by token and character by character."""
    char, place = [], -1  # the character of each byte
    for b in text.encode():
        place += (b & 0xC0) != 0x80
        char.append(place)
    lines = text.split("\n")
    ends, at = [], 0
    for k, line in enumerate(lines):
        at += len(line) + (k < len(lines) - 1)
        ends.append(at)
    if len(ends) > 1 and ends[-1] == ends[-2]:
        ends.pop()
    section = lambda c: next(k for k, e in enumerate(ends) if c < e)
    counts, crossing, byte = [0.0] * len(ends), [0] * len(ends), 0
    for i in enc.encode(text):
        n = len(enc.token[i])
        own = [section(c) for c in range(char[byte], char[byte + n - 1] + 1)]
        byte += n
        crossing[own[0]] += own[0] != own[-1]
        if rule == "first":
            counts[own[0]] += 1
        elif rule == "most":
            counts[max(sorted(set(own)), key=lambda k: (own.count(k), -k))] += 1
        else:
            for k in own:
                counts[k] += 1 / len(own)
    return [(k, ([0] + ends)[k], e, counts[k], crossing[k]) for k, e in enumerate(ends)]


@pytest.mark.parametrize("rule", tokencounts.RULES)
def test_token_counts_of_sections(spark, rule):
    enc = bpe.encoder(PATH, P.PATTERN)
    texts = [t for t in TEXTS if t is None or len(t) < 5000] + ["a\n\n\n  b\r\n", "é\n\té…\n\n", "\n", "x\n", "日本\n語 \n\n "]
    rows = tokencounts.tokens_by_section(frame(spark, texts), PATH, P.PATTERN, rule).collect()
    for i, t in enumerate(texts):
        got = sorted(tuple(r)[1:] for r in rows if r.doc_id == i)
        want = plain_sections(t or "", enc, rule)
        assert [g[:3] + g[4:] for g in got] == [w[:3] + w[4:] for w in want]
        assert all(abs(g[3] - w[3]) < 1e-9 for g, w in zip(got, want, strict=True))


def test_base_places_of_whole_documents(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").collect()
    got = {r.doc_id: r for r in queries.op10_license_notices(spark, sf_dir).collect()}
    assert len(got) == len(docs)
    for d in docs:
        words = WORD.findall((d.text or "").translate({c: c + 32 for c in range(65, 91)}))
        at = sorted((i, label) for phrase, label in licenses.PHRASES for i in range(len(words)) if words[i : i + len(phrase.split())] == phrase.split())
        r = got[d.doc_id]
        assert (r.n_words, r.n_base, r.base_labels) == (len(words), len(at), ",".join(sorted({x for _, x in at})))
        assert (r.first_word, r.last_word) == ((at[0][0], at[-1][0]) if at else (None, None))
        assert set(r.base_labels.split(",")) - {""} <= set(r.labels.split(",")) and 0 <= r.score <= 1


def test_very_long_licence_text_takes_linear_time():
    search = licenses.NoticeSearch()
    took = []
    for n in (20_000, 80_000):
        start = time.perf_counter()
        _, places, _ = search.scan(b"under the mit license " * n)
        took.append(time.perf_counter() - start)
        assert [w for w, _ in places[:3]] == [0, 4, 8] and places[-1][0] == 4 * (n - 1)
    assert took[1] < 12 * took[0]


@pytest.mark.parametrize("make", [lambda n: '<a href="x ' * n, lambda n: "<div><p>" * n, lambda n: "<!x " * n, lambda n: "<ul>" + "<b>" * n + "<li>x</li>" * n, lambda n: "</i>" * n + "<div>" * n + "</u>" * n])
def test_broken_markup_takes_linear_time(make):
    took = []
    for n in (5_000, 20_000):
        start = time.perf_counter()
        htmltext.main_text(make(n))
        took.append(time.perf_counter() - start)
    assert took[1] < 12 * took[0] + 0.05


def site(n, extra=""):
    return [(i, f"http://h{i % 2}.example.org/{i}", f"<html><body><div class=x{i % 2}>Site line {i % 2}</div>{extra}<p>Own words of page {i}.</p><p>More of {i}.</p></body></html>") for i in range(n)]


@pytest.mark.parametrize("most", [1 << 20, 0])
def test_templates_decide_on_pages_without_article(spark, most):
    pages = spark.createDataFrame(site(40) + [(99, None, "<p>No host</p>"), (98, "http://h0.example.org/98", None)], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in htmltext.main_texts(pages, most=most).collect()}
    for i in range(40):
        assert got[i] == f"Own words of page {i}.\nMore of {i}."
    assert got[99] == "No host" and got[98] == ""
    # by hand: a subtree stands in at least five pages of the host and a tenth of them
    few = spark.createDataFrame(site(8), "page_id long, url string, html string")
    assert all(r.text.startswith("Site line") for r in htmltext.main_texts(few).collect())


def test_cut_of_slices_equals_cut_of_one(spark):
    items = [(i, " ".join(f"w{(i * 7 + k) % 50}" for k in range(14))) for i in range(12)]
    texts = [" ".join(f"w{(i + k * (1 + i % 2)) % 60}" for k in range(80)) for i in range(20)] + [None, ""]
    bench, docs = spark.createDataFrame(items, "item_id long, text string"), frame(spark, texts + texts[:2])
    for remove in ("spans", "documents"):
        one, many = (sorted(((r.doc_id, r.text) for r in decontaminate.clean_documents(docs, bench, remove=remove, most_bytes=b).collect()), key=str) for b in (1 << 20, 50))
        assert one == many and any(brute_hits(t, items)[1] for t in texts)
