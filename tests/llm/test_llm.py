"""The text operators against brute force, with nulls, empty and long texts, ties, repeats and odd columns."""

import hashlib
import random
import re
from collections import Counter
from itertools import pairwise
from math import comb

import numpy as np
import pytest
import xxhash

from corefold.llm import anchors, bpe, debruijn, html_extract, licenses, packing, quality, queries, simhash, suffix, suffix_dedup, topk, windows

PATH = queries.bpe_path()
SCHEMA = "doc_id long, text string, lang string, tid long, part int, _t string, n_words long, n_chars long"


def table(spark, rows):
    """(doc_id, text) rows, with other columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "en", 7, 7, "x", 7, None if t is None else len(t)) for i, t in rows], SCHEMA)


def corpus(seed=0, n=60):
    rnd = random.Random(seed)
    vocabulary = ["alpha", "bé", "gamma", "d", "the", "of", "naïve", "zeta,", "eta.", "x1"]
    shared = " ".join(rnd.choice(vocabulary) for _ in range(70))
    base = [" ".join(rnd.choice(vocabulary) for _ in range(rnd.choice([3, 40, 120, 200]))) for _ in range(n)]
    texts = []
    for i, t in enumerate(base):
        kind = i % 6
        texts.append([t, t + "\n" + shared, shared + " " + t, base[i // 2], base[i // 2].replace("alpha", "ALPHA", 1), f"{t}\n{shared[: 5 * i]}"][kind])
    texts += [None, "", " \n\t", "one", "one", shared, shared + shared, "<|endoftext|> a  b<|endoftext|>\r\n", "word " * 3000]
    return [(3 * i + 1, t) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def rows():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return table(spark, rows).repartition(4)


def test_top_k(spark):
    rng = np.random.default_rng(0)
    vectors = rng.integers(-3, 4, (300, 6)) / 4.0
    vectors[100:160] = vectors[0]  # ties
    rows = [(i, v.tolist()) for i, v in enumerate(vectors)]
    rows += [(1000, None), (1001, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (1050, [float("nan")] * 6), (None, [0.0] * 6), (1100, [float("inf")] + [0.0] * 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(5)
    whole = np.floor(256 * vectors).astype(np.int64)
    for every, k, block in ((50, 5, 4096), (7, 3, 10)):
        got = {(r.query_id, r["rank"]): (r.vec_id, r.score) for r in topk.search(df, every, k, block=block).collect()}
        want = {}
        for q in range(0, 300, every):
            order = sorted((-int(whole[q] @ whole[c]), c) for c in range(300) if c != q)[:k]
            want |= {(q, i + 1): (c, -s) for i, (s, c) in enumerate(order)}
        assert got == want
    assert topk.search(df.filter("vec_id IN (0, 7, 14)"), 7, 5).count() == 6  # fewer than k
    assert topk.search(df.limit(0), 50).count() == 0


def test_top_k_of_large_components_and_several_lengths(spark):
    from math import floor

    rng = np.random.default_rng(1)
    vectors = {i: [float(np.float32(x)) for x in rng.normal(0, 1, 3 + i % 2)] for i in range(40)}
    vectors |= {50: [1e30, 1.0, -1e30], 51: [3e38, 3e38, 3e38], 52: [1e8, 5.0, 1.0], 53: [1e9, -1e7, 3.0], 54: [], 55: [0.0, 0.0, 0.0]}
    df = spark.createDataFrame(list(vectors.items()), "vec_id long, embedding array<double>").repartition(3)
    whole = {i: [floor(256 * x) for x in v] for i, v in vectors.items()}
    got = {}
    for r in topk.search(df, 5, 4, block=3).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    for q in (i for i in vectors if i % 5 == 0 and vectors[i]):
        scores = {c: sum(a * b for a, b in zip(whole[q], whole[c], strict=True)) for c in vectors if c != q and len(vectors[c]) == len(vectors[q])}
        held = sorted((-max(-topk.MOST, min(topk.MOST, s)), c) for c, s in scores.items())[:4]
        assert sorted(got[q]) == [(i + 1, c, -s) for i, (s, c) in enumerate(held)]


def brute_bytes(rows, w=100):
    seen, out = set(), {}
    for i, t in sorted(rows):
        data = (t or "").encode()
        gone = bytearray(len(data))
        for a in range(len(data) - w + 1):
            if data[a : a + w] in seen:
                gone[a : a + w] = b"\1" * w
            seen.add(data[a : a + w])
        kept = bytes(b for b, g in zip(data, gone, strict=True) if not g)
        out[i] = (len(data), sum(gone), sum(1 for x in bytes(gone).split(b"\0") if x), hashlib.sha256(kept).hexdigest())
    return out


@pytest.mark.parametrize("limits", [{}, {"hot": 1, "flush": 2000}, {"heavy": -10}])
def test_suffix_dedup(spark, docs, rows, limits):
    more = table(spark, [(None, "word " * 50)])
    got = suffix_dedup.remove_repeats(docs.unionByName(more), **limits).collect()
    want = brute_bytes(rows)
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got if r.doc_id is not None} == want
    assert [r.n_removed for r in got if r.doc_id is None] == [0]
    assert suffix_dedup.remove_repeats(docs.limit(0)).count() == 0


def test_clean_texts_keep_columns_and_whole_characters(spark, docs):
    out = suffix_dedup.clean_texts(docs)
    assert out.columns == docs.columns and out.count() == docs.count()
    assert all(r.n_chars == len(r.text) for r in out.collect() if r.text is not None)


@pytest.mark.parametrize("seed", range(30))
def test_suffix_order_and_prefixes(seed):
    rnd = random.Random(seed)
    data = bytes(rnd.randint(0, rnd.choice([1, 2, 9])) for _ in range(rnd.randint(1, 80)))
    data = data * rnd.choice([1, 3]) + bytes([5]) * rnd.choice([0, 25]) + b"\0"
    for memory in (1 << 20, 8):
        order, common = suffix.sorted_suffixes(np.frombuffer(data, dtype=np.uint8), 20, memory)
        assert sorted(order.tolist()) == list(range(len(data)))
        for (a, b), c in zip(pairwise(order.tolist()), common[1:].tolist(), strict=True):
            x, y = data[a:], data[b:]
            n = next((i for i, (p, q) in enumerate(zip(x, y, strict=False)) if p != q), min(len(x), len(y)))
            assert x[:20] <= y[:20] and min(n, 20) == c


def test_bpe_is_the_library(spark, docs, rows):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(PATH)
    odd = ["a\nb\n\nc", "a \nb", "\nx", "x\n", "a\r\nb", "end. Next, one;two", "a\n", "\n", " ", "A.b c", "a  b", "\n\n a\tb", "don't we'll 's\n's it", "\x00 a \x00b", "é ñ\n\nü ", "123 abc456 !!!\n ?", "\x1c a\x85b", "日本 語　x", "a b", "😀 👩‍👧"]
    more = table(spark, [(10_000 + i, t) for i, t in enumerate(odd)])
    texts = dict(rows) | {10_000 + i: t for i, t in enumerate(odd)}
    got = {r.doc_id: r for r in bpe.encode_decode(docs.unionByName(more), PATH, words=20, keep_ids=True).collect()}
    for i, t in texts.items():
        ids = library.encode(t or "", add_special_tokens=False).ids
        decoded = library.decode(ids, skip_special_tokens=False)
        assert got[i].ids == ids and got[i].decoded == decoded and got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256(decoded.encode()).hexdigest()
    assert bpe.encode_decode(docs.limit(0), PATH).count() == 0


def test_lexicon_is_minimal_and_exact(tmp_path):
    words = {b"tap": [1], b"taps": [2, 3], b"top": [4], b"tops": [5]}
    (tmp_path / "lexicon").write_bytes(bpe.compile_lexicon(words))
    lexicon = bpe.Lexicon(str(tmp_path / "lexicon"))
    found = lexicon.lookup([*words, b"ta", b"tapsx", b"q", b""])
    assert [None if x is None else np.frombuffer(x, "<u4").tolist() for x in found] == [*words.values(), None, None, None, None]
    assert len(lexicon.final) == 5  # root, t, a and o together, p, s
    vocabulary = bpe.Vocabulary(PATH)
    enc = bpe.Encoder(PATH)
    for word in (b" hello", b"naXve", "größe".encode(), b"aaaaaaaaaaa", b"!?!?"):
        assert vocabulary.merge(word) == enc._merge(word)


def test_token_counts(spark, docs, rows):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(PATH)
    sizes = [len(library.encode(t or "", add_special_tokens=False).ids) for _, t in rows]
    assert packing.length_histogram(packing.token_lengths(docs.limit(0), PATH)).count() == 0
    histogram = packing.length_histogram(packing.token_lengths(docs, PATH)).cache()
    for r in histogram.collect():
        n = r.n_tokens
        assert (r.n_docs, r.docs_longer, r.tokens_longer) == (sizes.count(n), sum(s > n for s in sizes), sum(s for s in sizes if s > n))
        assert r.truncated_total == sum(min(s, n) for s in sizes) and r.quantile == sum(s <= n for s in sizes) / len(sizes)
    one = packing.at_limit(histogram, 100).first()
    assert one.truncated_total == sum(min(s, 100) for s in sizes) and one.docs_truncated == sum(s > 100 for s in sizes)


def test_packing(spark, docs, rows):
    import zlib

    from tokenizers import Tokenizer

    library = Tokenizer.from_file(PATH)
    got = packing.pack(docs.unionByName(table(spark, [(1, rows[0][1])])), PATH, limit=256, end_id=2).collect()
    ids = {i: [*library.encode(t or "", add_special_tokens=False).ids, 2] for i, t in rows}
    assert sum(r.length for r in got) == sum(map(len, ids.values())) + len(ids[1])
    used = {}
    for r in got:
        piece = ids[r.doc_id][r.start : r.start + r.length]
        assert len(piece) == r.length <= 256 and zlib.crc32(np.array(piece, "<u4").tobytes()) == r.ids_crc32
        assert r.length == 256 or r.piece == 0
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for spans in used.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 256
    assert packing.pack(docs.limit(0), PATH).count() == 0


@pytest.mark.parametrize("seed", range(20))
def test_best_fit_plan(seed):
    rnd = random.Random(seed)
    limit = rnd.choice([10, 64, 1024])
    counts = {rnd.randint(1, limit): rnd.randint(1, 10 ** rnd.randint(0, 5)) for _ in range(rnd.randint(1, 60))}
    plan = packing.plan_best_fit(counts, limit)
    placed = Counter()
    for pattern, n in plan:
        assert sum(size * k for size, k in pattern) <= limit
        for size, k in pattern:
            placed[size] += k * n
    assert placed == counts and len(plan) <= 4 * limit
    if sum(counts.values()) < 20_000:  # one item at a time: smallest room that fits
        rooms = []
        for size in sorted((s for s, n in counts.items() for _ in range(n)), reverse=True):
            fit = min((r for r in set(rooms) if r >= size), default=None)
            rooms.append(limit - size) if fit is None else rooms.__setitem__(rooms.index(fit), fit - size)
        assert sum(n for _, n in plan) == len(rooms)


def test_html(spark):
    page = "<html><head><title>T</title><script>var t='</p>';</script></head><body><nav><ul><li><a href=/a>Home</a></li></ul></nav><div class='ad'>Buy now</div><article><h1>Head &amp; more</h1><p>First <b>bo</b>ld  text\n here.<p>Second<br>line with <a href='/x'>a link</a>.<div class=ad>Advert words</div><p>Third &lt;p&gt;.</article><section class='comments'><p>I like it a lot and say so</p></section><footer>&copy; us</footer>"
    rows = [(1, "u", page), (2, None, None), (3, "", ""), (None, "u", "<p>a < b and c > d"), (1, "u", page), (4, "v", "<nav>only menu</nav>"), (5, "w", "plain words")]
    got = [tuple(r) for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)).collect()]
    want = "Head & more First bold text here. Second line with a link. Third <p>."
    assert [g[2] for g in got] == [want, "", "", "a < b and c > d", want, "", "plain words"]
    assert all(len(g[2]) == g[3] for g in got)


def test_html_on_held_out_pages(spark, sf):
    for r in spark.read.parquet(f"{sf}/pages.parquet").collect():
        import html

        inner = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        want = " ".join(html.unescape(re.sub(r"</?b>", "", re.sub(r"<(?!/?b>)[^>]*>", " ", inner))).split())
        assert html_extract.extract(r.html) == want


PARAGRAPH = "<p>Some real article text that goes on with many words, and then more words follow it here.</p>"


@pytest.mark.parametrize("before", ["<script>if(a<b){x()}</script>", "<script>for(i=0;i<n;i++){}</script>", "<script>var a='<!--';</script>", "<style>a<b{c:'</p>'}</style>", "<textarea><p>x</textarea>", "<SCRIPT src=a>'</scripty>'</Script >", "<title>a<b</title>", "<!-- <article> -->", "<noscript><p>enable</noscript>"])
def test_what_is_within_scripts_is_no_markup(before):
    want = "Head line " + " ".join([PARAGRAPH[3:-4]] * 4)
    for page in (f"<html><body>{before}<article><h1>Head line</h1>{PARAGRAPH * 4}</article><footer>foot</footer></body></html>", f"<article><h1>Head line</h1>{before}{PARAGRAPH * 4}</article><script>never ends a<b"):
        assert html_extract.extract(page) == want


def test_boxes_and_links_within_an_article():
    box = "<div class='newsletter'><form><label>Mail me now</label></form>" + "buy this word now please " * 30 + "</div>"
    lead, links = "<p>One lead stands here.</p>", "<ul><li><a href=/x>see one</a></li><li><a href=/y>see two</a></li></ul>"
    want = "See all Head line One lead stands here. " + " ".join([PARAGRAPH[3:-4]] * 3) + " see one see two"
    for name in ("article", "main"):
        page = f"<body><nav><a href=/>Home</a></nav><{name}><p><a href=/all>See all</a></p><h1>Head line</h1>{lead}{box}{PARAGRAPH * 3}{links}</{name}><ul><li><a href=/z>other</a></li></ul>"
        assert html_extract.extract(page) == want
    page = f"<body><div class='post'><h1>Head line</h1>{lead}{box}{PARAGRAPH * 3}</div><footer>foot</footer>"
    assert html_extract.extract(page) == "Head line One lead stands here. " + " ".join([PARAGRAPH[3:-4]] * 3)


def test_long_and_deep_pages(spark):
    deep = "<div class=a>" * 30_000 + PARAGRAPH * 3
    long = "<article>" + PARAGRAPH * 60_000 + "</article>"
    rows = [(1, "u", deep), (2, "u", long), (3, "u", "<" * 100_000), (4, "u", "x" * 1_000_000), (5, "u", "<!--" * 10_000), (6, "u", "<a <b " * 10_000)]
    got = {r.page_id: r for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1].text == " ".join([PARAGRAPH[3:-4]] * 3) and got[2].n_chars == 60_000 * (len(PARAGRAPH) - 6) - 1 and got[4].n_chars == 1_000_000 and got[5].text == ""
    empty = spark.createDataFrame([], "page_id long, url string, html string, text string, n_chars long")
    assert html_extract.extract_pages(empty).collect() == []


def shapes(article, menu, notes):
    """Pages whose make-up is none of labelled_pages(): (html)."""
    links = "".join(f"<li><a href='/{i}'>{w}</a></li>" for i, w in enumerate(menu))
    bar = f"<div class='topbar'><ul>{links}</ul></div>"
    return [
        f"<body><div id='wrapper'>{bar}<div class='col-8'>{article}</div><div class='col-4'><h4>{notes}</h4><ul>{links}</ul></div></div><div class='legal'><a href='/l'>{notes}</a></div></body>",
        f"<body><table><tr><td><ul>{links}</ul></td><td>{article}</td></tr></table><small><a href='/'>{notes}</a></small></body>",
        f"<body><nav>{bar}</nav><main><div><div>{article}</div></div></main><footer><div><span>{notes}</span></div></footer></body>",
        f"<body><header><a href='/'>{notes}</a></header><section><div class='story-body'>{article}</div></section><aside><p>{notes}</p></aside></body>",
        f"<body>{bar}{article}<ul>{links}</ul></body>",
        f"<html><head><script>if(a<b)x('<nav>')</script></head><body><div role='navigation'>{links}</div><div class='text'>{article}</div><div class='comments'><p>{notes}</p></div></body></html>",
    ]


def test_html_precision_and_recall_on_other_shapes(spark, sf):
    right = found = wanted = 0
    for r in spark.read.parquet(f"{sf}/pages.parquet").limit(25).collect():
        article = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        want = Counter(html_extract.extract(f"<article>{article}</article>").split())
        menu = re.findall(r"<li><a[^>]*>([^<]*)</a>", r.html) or ["Home", "News"]
        for page in shapes(article, menu, "Some notes at the edge"):
            got = Counter(html_extract.extract(page).split())
            right, found, wanted = right + (got & want).total(), found + got.total(), wanted + want.total()
    print("precision", right / found, "recall", right / wanted)
    assert right / found > 0.97 and right / wanted > 0.99


def test_licenses(spark, docs, rows):
    texts = ["Licensed under the Apache License, Version 2.0. All rights reserved.", "CC-BY cc by CC  BY", "Released under the MIT License", "SPDX-License-Identifier: MPL-2.0", "x cc byte", "All Rights\nReserved and general public license all rights reserved", None, "", "mit der Zeit"]
    own = list(enumerate(texts, 5000))
    got = {r.doc_id: r for r in licenses.scan(docs.unionByName(table(spark, own))).collect()}
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    for i, t in [*rows, *own]:
        lower = re.sub("[A-Z]+", lambda m: m[0].lower(), t or "")
        ws, places, labels = word.findall(lower), [], set()
        for phrase, label in licenses.BASE_PHRASES.items():
            p = phrase.split()
            hits = [a for a in range(len(ws) - len(p) + 1) if ws[a : a + len(p)] == p]
            places += hits
            labels |= {label} if hits else set()
        r = got[i]
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (len(ws), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels)))
        assert labels <= set(r.labels.split(",")) and 0 <= r.score <= 1
    assert "apache-2.0" in got[5000].labels and "mit" in got[5002].labels and got[5002].score == 0.9
    assert got[5003].labels == "mpl-2.0" and got[5003].score == 1.0 and got[5008].labels == "" and got[5004].labels == ""


def test_license_prefilter_lets_every_rule_through():
    known = set(licenses.keywords(licenses.rules()))
    assert len(licenses.rules()) > 200
    for line in licenses.FAMILIES:
        for name in line.split(": ")[1].split("|"):
            assert known & {w for w in name.split() if not w.endswith("?")}


def license_examples():
    """(label, text): each name in each form, with and without what may lack; bare names; notices."""
    out = []
    for line in licenses.FAMILIES:
        label, names = line.split(": ")
        for name in names.split("|"):
            plain = " ".join(w for w in name.split() if not w.endswith("?"))
            out += [(label, f"x {verb} under {plain} y") for verb in ("Licensed", "Released", "distributed", "provided")]
            out += [(label, f"x available under {a} {plain} y") for a in ("a", "the", "the terms of the")]
            out.append((label, f"SPDX-License-Identifier: {plain}"))
            if "license" not in plain.split():
                out += [(label, f"x {t}{plain} License y") for t in ("", "the ")] + [(label, f"license: {plain}")]
            if len(name.split()) >= 2:
                out.append((label, f"x {plain.upper()} y"))
    out += [("public-domain", "x Public Domain y"), ("public-domain", "put into the public domain"), ("reserved", "some rights reserved")]
    out += [("warranty-disclaimer", "without warranty of any kind"), ("warranty-disclaimer", "without warranties of any kind"), ("proprietary", "proprietary and confidential")]
    return out


def test_every_form_of_every_license_rule_is_found(spark):
    examples = license_examples()
    got = {r.doc_id: r for r in licenses.scan(table(spark, [(i, t) for i, (_, t) in enumerate(examples)])).collect()}
    # a version counts as found if its family is
    family = lambda label: label.split("-")[0]
    missed = [(label, t, got[i].labels) for i, (label, t) in enumerate(examples) if not any(family(label) == family(x) for x in got[i].labels.split(","))]
    assert missed == []


WORD = re.compile("[^\x20\x09-\x0d]+")


def brute_measures(t, window=5):
    t = t or ""
    ws = WORD.findall(t)
    grams = Counter(tuple(ws[a : a + window]) for a in range(len(ws) - window + 1))
    cover = {b for a in range(len(ws) - window + 1) if grams[tuple(ws[a : a + window])] > 1 for b in range(a, a + window)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(ws), sum(map(len, ws)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover)


def test_quality_measures_and_base(spark, docs, rows):
    more = [(9001, "a b c d e a b c d e x " * 2 + "\nline one\nline one\n \n"), (9002, "# $ % <|> !! && ok"), (9003, None)]
    labels = spark.createDataFrame([(1, 1), (None, 0), (4, None), (99999, 0)], "doc_id long, quality int")
    source = docs.unionByName(table(spark, more))
    source = source.selectExpr("*", "'keep' AS _w", "1 AS _g", "2 AS row", "3 AS kept", "4 AS stratum")
    judged = quality.judge(source, labels)
    assert judged.select("row.*").columns == source.columns
    got = {r.row.doc_id: r for r in judged.collect()}
    for i, t in [*rows, *more]:
        r = got[i]
        want = brute_measures(t)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0]) and r.kept == (not r.base_failed)  # too few labels certify nothing
        assert (r.row._w, r.row._g, r.row._t, r.row.n_words, r.row.text) == ("keep", 1, "x", 7, t)
    assert quality.judge(source.limit(0), labels).count() == 0
    assert quality.judge(source, labels.limit(0)).filter("NOT kept AND NOT base_failed").count() == 0


def tail(k, n, p):
    return sum(comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1))


def test_binomial_tail_is_exact(spark):
    from pyspark.sql import functions as F

    cases = [(0, 500), (3, 500), (20, 400), (7, 7), (0, 0), (90, 3000)]
    got = [r.p for r in spark.createDataFrame(cases, "k long, n long").select(quality.binomial_tail(F.col("k"), F.col("n"), 0.02).alias("p")).collect()]
    for (k, n), p in zip(cases, got, strict=True):
        assert abs(p - (1.0 if n == 0 else tail(k, n, 0.02))) < 1e-9
    # far beyond what one term could hold: the normal limit
    p = spark.sql("SELECT 59000L AS k, 3000000L AS n").select(quality.binomial_tail(F.col("k"), F.col("n"), 0.02).alias("p")).first().p
    from statistics import NormalDist

    assert abs(p - NormalDist(60000, (3_000_000 * 0.02 * 0.98) ** 0.5).cdf(59000.5)) < 1e-4


def labelled_corpus():
    """(id, text, stratum, quality or None): strata with many, few and no labels; junk by symbols, shouts and long words."""
    rnd, out = random.Random(5), []
    words = [f"word{i}" for i in range(300)]
    for stratum, n in (("a", 1600), ("b", 700), ("c", 60), (None, 600), ("d", 0)):
        for i in range(n + 80):
            text = [rnd.choice(words) for _ in range(rnd.randint(12, 40))]
            kind = rnd.random()
            quality_ = 1
            if kind < 0.08:
                text[::2], quality_ = ["###"] * len(text[::2]), 0
            elif kind < 0.12:
                text, quality_ = [w + "!" * rnd.randint(1, 4) for w in text], 0
            elif kind < 0.15:
                text, quality_ = [w * 9 for w in text], 0
            elif kind < 0.17:
                text[3] = "!!"  # good ones that shout a little
            elif kind < 0.18:
                text = text[:5]
            if rnd.random() < 0.02:
                quality_ = 1 - quality_
            out.append((len(out) + 1, " ".join(text), stratum, quality_ if i < n else None))
    return out


def percentile(values, level):
    at = level * (len(values) - 1)
    low, high = int(np.floor(at)), int(np.ceil(at))
    return values[low] if low == high or values[low] == values[high] else (high - at) * values[low] + (at - low) * values[high]


def brute_kept(judged, labels, risk, error):
    """kept of each id, by the module's method, from its measures, in plain Python."""
    import xxhash

    value = {r.row.doc_id: {"symbols": r.n_symbols / max(r.n_words, 1), "shouts": r.n_shouts / max(r.n_words, 1), "dup_lines": r.n_dup_lines / max(r.n_lines, 1), "repeats": r.n_repeat_words / max(r.n_words, 1), "long_words": r.word_chars / max(r.n_words, 1), "short_words": -r.word_chars / max(r.n_words, 1)} for r in judged}
    tune = {i: (xxhash.xxh64_intdigest(i.to_bytes(8, "little"), 42) - (1 << 64 if xxhash.xxh64_intdigest(i.to_bytes(8, "little"), 42) >> 63 else 0)) % quality.TUNE == 0 for i in value}
    held = {r.row.doc_id: (r.row.lang, labels[r.row.doc_id]) for r in judged if not r.base_failed and labels.get(r.row.doc_id) is not None}
    chosen = {}
    for stratum in {s for s, _ in held.values()}:
        found = []
        for rule in quality.rates():
            good = sorted(value[i][rule] for i, (s, q) in held.items() if s == stratum and q == 1 and tune[i])
            bad = [value[i][rule] for i, (s, q) in held.items() if s == stratum and q == 0 and tune[i]]
            cuts = {percentile(good, level) for level in quality.LEVELS} if good else set()
            if cuts:
                cuts.add(2 * percentile(good, quality.LEVELS[-1]) - percentile(good, quality.LEVELS[0]))
            tried = [(sum(v > c for v in bad) - quality.COST * sum(v > c for v in good), c) for c in cuts]
            if tried and max(tried)[0] > 0:
                c, worth = max((c, w) for w, c in tried if w >= quality.NEARLY * max(tried)[0])
                found.append((-worth, rule, c))
        if found:
            chosen[stratum] = [(rule, c) for _, rule, c in sorted(found)]
    limits = {}
    for stratum, rules in chosen.items():
        good = [i for i, (s, q) in held.items() if s == stratum and q == 1 and not tune[i]]
        limits[stratum] = []
        for n in range(1, len(rules) + 1):
            k = sum(any(value[i][r] > c for r, c in rules[:n]) for i in good)
            if not good or tail(k, len(good), risk) > error / len(chosen):
                break
            limits[stratum] = rules[:n]
    return {r.row.doc_id: not r.base_failed and not any(value[r.row.doc_id][rule] > c for rule, c in limits.get(r.row.lang, [])) for r in judged}, limits


def test_certified_cutoffs_are_those_of_plain_python(spark):
    corpus_ = labelled_corpus()
    docs = spark.createDataFrame([r[:3] for r in corpus_], "doc_id long, text string, lang string").repartition(3)
    labels = spark.createDataFrame([(i, q) for i, _, _, q in corpus_ if q is not None], "doc_id long, quality int")
    judged = quality.judge(docs, labels).collect()
    want, limits = brute_kept(judged, {i: q for i, _, _, q in corpus_}, quality.RISK, quality.ERROR)
    assert {r.row.doc_id: r.kept for r in judged} == want
    assert len(limits["a"]) >= 2 and limits["b"] and limits[None] and not limits.get("c") and "d" not in limits
    # what is certified holds for the unlabelled ones too
    for stratum in ("a", "b", None):
        lost = [r.kept for r in judged if r.row.lang == stratum and not r.base_failed and corpus_[r.row.doc_id - 1][3] is None and "#" not in r.row.text and "!" not in r.row.text and r.word_chars < 20 * r.n_words]
        assert sum(not x for x in lost) <= 0.05 * len(lost)


def brute_fingerprint(t, size=3):
    ws = (t or "").encode().lower().split()
    if not ws:
        return 0
    hs = [xxhash.xxh64_intdigest(b" ".join(ws[i : i + size]), seed=42) for i in range(max(1, len(ws) - size + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


@pytest.mark.parametrize("pairwise_limit", [None, 1])
def test_simhash(spark, docs, rows, pairwise_limit, monkeypatch):
    monkeypatch.setattr(simhash.links, "__defaults__", (2, pairwise_limit))
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_duplicates(docs.unionByName(table(spark, [(None, "one")]))).collect()}
    assert got.pop(None)[1] is None
    prints = {i: brute_fingerprint(t) for i, t in rows}
    root = {i: i for i in prints}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in prints:
        for b in prints:
            if a < b and (prints[a] ^ prints[b]).bit_count() <= 2:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    assert got == {i: (f"{p:016x}", find(i)) for i, p in prints.items()}
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_chains_of_fingerprints_are_one_component(spark):
    chain = [0]
    for b in range(0, 60, 2):
        chain.append(chain[-1] ^ (3 << b))
    fps = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in chain], "fp long")
    for limit in (None, 2):
        roots = {r.root for r in simhash.components(simhash.links(fps, 2, limit)).collect()}
        assert len(roots) == 1


def test_one_of_each_class_stays(spark, docs, rows):
    out = simhash.deduplicate(docs.unionByName(docs.limit(5)).unionByName(table(spark, [(None, "one")])))
    assert out.columns == docs.columns
    left = [r.doc_id for r in out.collect()]
    assert left.count(None) == 1 and len(left) == len(set(left))
    texts = {}
    for i, t in rows:
        texts.setdefault(t or "", i)
    assert set(left) - {None} <= set(texts.values()) | {i for i, t in rows if not (t or "").split()}


def brute_words(rows, w=50):
    words = {i: (t or "").encode().split() for i, t in rows}
    first = {}
    for i in sorted(words):
        for a in range(len(words[i]) - w + 1):
            first.setdefault(tuple(words[i][a : a + w]), i)
    out = {}
    for i, ws in words.items():
        gone = [False] * len(ws)
        for a in range(len(ws) - w + 1):
            if first[tuple(ws[a : a + w])] < i:
                gone[a : a + w] = [True] * w
        kept = [x for x, g in zip(ws, gone, strict=True) if not g]
        out[i] = (len(ws), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


@pytest.mark.parametrize("limits", [{}, {"heavy": -10, "flush": 2000}, {"bits": 8}])
def test_debruijn(spark, docs, rows, limits):
    """With 8 bits of each hash different words meet, which their sources' words show."""
    more = table(spark, [(None, "word " * 60)])
    got = debruijn.remove_repeats(docs.unionByName(more), **limits).collect()
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in got if r.doc_id is not None} == brute_words(rows)
    assert [r.n_removed for r in got if r.doc_id is None] == [0]
    assert all((r.n_paths > 0) == (r.n_removed > 0) for r in got)
    assert debruijn.remove_repeats(docs.limit(0)).count() == 0


def test_equal_first_hashes_alone_make_no_class():
    key = np.array([5, 5, 5, 7], dtype=np.uint64)
    other = np.array([1, 2, 1, 1], dtype=np.uint64)
    c = windows.classes((key, other), np.array([3, 1, 2, 0]), np.zeros(4, dtype=np.int64), False)
    assert {(int(r), int(lead)) for r, lead, again in zip(c.order, c.lead, c.repeat, strict=True) if again} == {(0, 2)}


def test_long_texts(spark):
    """Megabytes in one text, with and without white space, that repeat themselves."""
    rnd = random.Random(3)
    block = "".join(rnd.choice("abcdef") for _ in range(40_000))
    words = " ".join(rnd.choice(["ab", "cd", "ef", "gh"]) + str(rnd.randrange(1000)) for _ in range(20_000))
    rows = [(1, block * 30), (2, words * 8), (3, words), (4, block)]
    docs = table(spark, rows)
    got = {r.doc_id: r for r in suffix_dedup.remove_repeats(docs).collect()}
    assert [got[i].n_bytes - got[i].n_removed for i in (1, 2, 3, 4)] == [len(block), len(words), 0, 0]
    assert got[1].kept_sha256 == hashlib.sha256(block.encode()).hexdigest() and got[2].kept_sha256 == hashlib.sha256(words.encode()).hexdigest()
    by_words = {r.doc_id: (r.n_words, r.n_removed) for r in debruijn.remove_repeats(docs).collect()}
    assert by_words[3] == (20_000, 20_000) and by_words[1] == (1, 0) and by_words[2][1] == 0
    library = bpe.Encoder(PATH)
    counted = {r.doc_id: r.n_tokens for r in packing.token_lengths(docs, PATH).collect()}
    assert counted == {i: len(library.slow(t)) // 4 for i, t in rows}


@pytest.mark.parametrize("seed", [1, 2])
def test_repeats_in_other_corpora(spark, seed):
    rows = corpus(seed, 40)
    docs = table(spark, rows).repartition(3)
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in debruijn.remove_repeats(docs).collect()} == brute_words(rows)
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(docs).collect()} == brute_bytes(rows)


def test_contexts_that_share_only_an_anchor_are_not_sorted(spark):
    """A phrase too short to repeat leaves nothing open; one of 100 bytes does, on whichever side the anchor lies."""
    rnd = random.Random(8)
    noise = lambda n: "".join(rnd.choice("abcdefghij klmnop") for _ in range(n))
    short, long = noise(60), noise(100)
    opened = {}
    for name, phrase in (("short", short), ("long", long)):
        rows = [(i, noise(300) + phrase + noise(300)) for i in range(20)]
        docs = spark.createDataFrame(rows, "doc_id long, text string")
        found = windows.repeated(windows.identified(docs), windows.Spec(100, 32, words=False, by_doc=False), 8)
        opened[name] = {r.doc_id for r in found.filter("length(open) > 0").collect()}
        assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(docs).collect()} == brute_bytes(rows)
    assert opened == {"short": set(), "long": set(range(20))}


@pytest.mark.parametrize(("w", "k"), [(100, 32), (50, 12), (8, 3), (9, 9)])
def test_equal_windows_share_a_side_of_their_anchor(w, k):
    rnd = np.random.default_rng(w)
    texts = [bytes(rnd.integers(97, 100, rnd.integers(0, 400)).astype(np.uint8)) for _ in range(40)]
    texts += [t[rnd.integers(0, 50) :][: rnd.integers(50, 300)] + texts[3][10:60] for t in texts]
    codes, begin = windows.symbols(texts, False)
    found, whole = anchors.Anchors(codes, begin, w, k), b"".join(texts)
    before, after = anchors.sides(found.alt)
    places = {}
    for i, (a, b) in enumerate(zip(found.first.tolist(), found.last.tolist(), strict=True)):
        for s in range(a, b + 1):
            places.setdefault(whole[s : s + w], []).append(i)
    pairs = [(own[0], i) for own in places.values() for i in own[1:]]
    assert pairs and all(found.h[i] == found.h[j] and (before[i] == before[j] > 0 or after[i] == after[j] > 0) for i, j in pairs)
