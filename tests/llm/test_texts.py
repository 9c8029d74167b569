"""Kernels of the text operators against brute force, without Spark."""

import re
import struct
import time

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from splitguard.llm import decontam, exactdedup, htmltext, langid, licences, sentencepieces, simhash, weakquality

words = st.lists(st.sampled_from("a b ab ba abc the of x1".split()), max_size=40)


# ---- SimHash ----------------------------------------------------------------------


def plain_fingerprint(text):
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    parts = re.findall(r"[^\x20\x09-\x0D]+", lowered)
    if not parts:
        return 0
    n = max(1, len(parts) - 3)
    hashes = [xxhash.xxh64_intdigest(" ".join(parts[i : i + 4]).encode(), 42) for i in range(n)]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > n)


@given(st.text(alphabet="aB \t\né \x0b", max_size=400))
@settings(max_examples=60, deadline=None)
def test_fingerprint_is_the_plain_one(text):
    assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_fingerprint_of_a_long_text():
    text = " ".join(f"Word{i % 977}" for i in range(5000))
    assert simhash.fingerprint(text) == plain_fingerprint(text)
    assert simhash.fingerprint(None) == simhash.fingerprint(" \n") == 0


def components(prints, links):
    parent = {p: p for p in prints}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    return {p: root(p) for p in prints}


@pytest.mark.parametrize("size, spread", [(40, 3), (400, 4), (700, 12)])
def test_dense_links_connect_what_all_pairs_connect(size, spread):
    rng = np.random.default_rng(size)
    centres = rng.integers(0, 1 << 63, 3, dtype=np.uint64)
    prints = set()
    for _ in range(size):
        x = int(rng.choice(centres))
        for b in rng.integers(0, 64, rng.integers(0, spread + 1)):
            x ^= 1 << int(b)
        prints.add(x)
    prints = np.array(sorted(prints), np.uint64)
    links = simhash.dense_links(prints, 4)
    assert all((a ^ b).bit_count() <= 4 for a, b in links)
    truth = [(int(a), int(b)) for i, a in enumerate(prints) for b in prints[i + 1 :] if (int(a) ^ int(b)).bit_count() <= 4]
    ints = [int(p) for p in prints]
    assert components(ints, links) == components(ints, truth)
    assert len(links) < len(prints)
    a, b = simhash.run_links(np.zeros(len(prints), np.int64), prints, 4)
    assert components(ints, zip(a.tolist(), b.tolist())) == components(ints, truth)


def test_blocks_cover_all_bits():
    layout, agree = simhash.block_layout(4, 6)
    assert sum(w for _, w in layout) == 64 and agree == 2
    with pytest.raises(ValueError):
        simhash.block_layout(4, 4)


# ---- Golomb-Rice ---------------------------------------------------------------------


@given(st.sets(st.integers(0, (1 << 48) - 1), max_size=200))
@settings(max_examples=60, deadline=None)
def test_rice_code_round_trip(values):
    sorted_values = np.array(sorted(values), np.int64)
    k, code = exactdedup.rice_encode(sorted_values)
    assert exactdedup.rice_decode(len(values), k, code).tolist() == sorted_values.tolist()


def test_rice_code_is_small():
    values = np.sort(np.random.default_rng(1).choice(1 << 24, 1 << 14, replace=False))
    _, code = exactdedup.rice_encode(values)
    assert len(code) * 8 < 13 * len(values)  # about ten bits of gap, and two


# ---- language ------------------------------------------------------------------------


def test_recogniser_and_ties():
    judge = langid.Recogniser({"aa": b" kitanuma sorito vellam " * 300, "bb": b" groth schwendel pfing " * 300}).judge
    assert judge("Kitanuma sorito vellam kitanuma")[0] == "aa"
    assert judge("PFING! groth, schwendel... 12")[0] == "bb"
    language, margin = judge("zzz")
    assert language == "aa" and 0 <= margin <= 1
    assert langid.Recogniser({}).judge("abc") == ("und", 0.0)
    assert langid.Recogniser({"aa": b"x" * 2000}).judge("abc") == ("aa", 1.0)


# ---- pages ---------------------------------------------------------------------------


@pytest.mark.parametrize(
    "page, text",
    [
        (None, ""),
        ("", ""),
        ("<p>One &amp; two</p>\n<p>three  <b>fo</b>ur</p>", "One & two three four"),
        ("<html><head><title>t</title><style>p{}</style></head><body><nav><p>menu</p></nav><article><h1>Head</h1>"
         "<p>Long enough text to be an article of its own, with many words in it.</p><p>End.</p></article>"
         "<footer>foot</footer>", "Head Long enough text to be an article of its own, with many words in it. End."),
        ("<div class='sidebar'><div>in</div>side</div><main>body text</main>", "body text"),
        ("<article>kept<section id='comments'><p>reader</p></section><form>f</form><script>var a='</p>'</script>!</article>", "kept !"),
        ("<article>a &lt;b&gt; c<!-- <p>no</p> --> d</article", "a <b> c d"),
        ("<article>x < y and <br>z</article>", "x < y and z"),
        ("<ul><li><a href=x>one</a></li><li><a href=y>two</a></li></ul><p>" + "Real text of the page goes here. " * 4 + "</p><div class=footer>f</div>",
         ("Real text of the page goes here. " * 4).strip()),
        ('<article>a<div title="x>y" class="ad-box">ad</div> b</article>', "a b"),
        ("<article><div class='shadow'>kept</div></article>", "kept"),
        ("<div class='page with-sidebar'><article>kept</article><div class=sidebar>side</div></div>", "kept"),
        ("<div id='menu'><main>kept</main></div>", "kept"),
    ],
)
def test_main_text(page, text):
    assert htmltext.main_text(page) == text


def test_a_page_of_many_blocks_is_kept_whole():
    page = "<body><article>" + "".join(f"<p>w{i}</p>" for i in range(5000)) + "</article></body>"
    assert htmltext.main_text(page) == " ".join(f"w{i}" for i in range(5000))


@pytest.mark.parametrize(
    "page, text",
    [
        ("<article><p>Body of the article, long enough.</p><figure><img src=x><figcaption>What it shows</figcaption></figure>"
         "<p>E = <math><mi>m</mi></math>.</p></article>", "Body of the article, long enough. What it shows E = m."),
        ("<article><div class='notice-board-history'>kept</div><div id=search-theory>too</div><div class=siteFooter>no</div></article>", "kept too"),
        ("<article class=teaser><p>Short teaser.</p></article>" + "<div><p>A paragraph of the real text of this page.</p></div>" * 30,
         " ".join(["A paragraph of the real text of this page."] * 30)),
        ("<article><p>First part of the article.</p></article><div class=ad>x</div><article><p>Second part.</p></article>",
         "First part of the article. Second part."),
        ("<main><h1>Title</h1><article><p>The words of the article.</p></article><ul><li><a href=x>more</a></li></ul></main>", "Title The words of the article."),
        ("<div>" + "<p>A first paragraph that is long enough to surge by itself, surely.</p>" * 3 + "<p>one</p>" * 7
         + "<p>A last paragraph that is long enough to surge by itself, surely.</p>" * 2 + "</div><p><a href=x>menu</a></p>",
         " ".join(["A first paragraph that is long enough to surge by itself, surely."] * 3 + ["one"] * 7
                  + ["A last paragraph that is long enough to surge by itself, surely."] * 2)),
        ("<article><p>The words of the article.</p><div class=ad-slot>Buy it</div><div id=readerComments><p>First!</p></div></article>",
         "The words of the article."),
        ("<article>a <span class=ad>b <span>c</span></span> d</article>", "a d"),
    ],
)
def test_regions_and_hints(page, text):
    assert htmltext.main_text(page) == text


@given(st.lists(st.integers(0, 90), max_size=30), st.integers(1, 5))
@settings(max_examples=100, deadline=None)
def test_regions_are_the_plain_ones(weights, window):
    width = min(window, len(weights))
    starts = range(len(weights) - width + 1) if weights else []
    assert htmltext.window_sums(weights, window) == [sum(weights[i : i + width]) for i in starts]
    covered = {j for i in starts if sum(weights[i : i + width]) >= 60 for j in range(i, i + width)}
    found = htmltext.regions(weights, window, 60)
    inside = {j for s, e in found for j in range(s, e)}
    assert {j for j in inside if weights[j]} == {j for j in covered if weights[j]}
    assert all(weights[s] and weights[e - 1] for s, e in found)
    assert all(a[1] < b[0] for a, b in zip(found, found[1:]))


def test_surge_and_dive_decide(monkeypatch):
    import duckdb

    pages = [h for (h,) in duckdb.sql("SELECT html FROM '/root/testdata/sf0.01/pages.parquet'").fetchall()]
    whole = [htmltext.main_text(h) for h in pages]
    bare = [htmltext.main_text(re.sub("(</?)article", r"\1div", h)) for h in pages]
    assert sum(a == b for a, b in zip(whole, bare)) >= 0.98 * len(pages)
    monkeypatch.setattr(htmltext, "regions", lambda *a, **k: [])
    assert all(htmltext.main_text(h) == "" for h in pages)


@pytest.mark.parametrize("unit", ['<a "', "<a '>", "<script", "<script>", "<!--", "<div>", "<p>x</p>", "<article>", "<", "class=", "&amp", "</", '<a ">" ', "<main>x"])
def test_hostile_pages_take_linear_time(unit):
    page = unit * (1_000_000 // len(unit))
    began = time.perf_counter()
    htmltext.main_text(page + ">")
    htmltext.main_text(page)
    assert time.perf_counter() - began < 10


def test_regions():
    assert htmltext.regions([0, 0, 0]) == []
    assert htmltext.regions([]) == [] and htmltext.window_sums([], 3) == []
    assert htmltext.regions([50, 20, 0, 0, 0, 0, 90]) == [(0, 2), (6, 7)]


# ---- licences ----------------------------------------------------------------------------


def test_licence_notices():
    scanner = licences.Scanner()
    text = "Some words first.\nLicensed under CC BY-NC 4.0.\nAnd after. Released under the MIT License. end"
    found = scanner.scan(text)
    assert [x[0] for x in found] == ["CC-BY-NC-4.0", "MIT"]
    assert text[found[0][2] : found[0][3]] == "Licensed under CC BY-NC 4.0"
    assert scanner.scan(None) == scanner.scan("") == scanner.scan("license") == []
    for name, texts in licences.NOTICES.items():
        for t in texts:
            assert (name, 1.0) in [(n, d) for n, d, _, _ in scanner.scan("lead in words. " + t + " trailing words")]


def plain_licences(text, notices, least=0.8):
    """All windows of all starts compared, then the best ones that don't overlap, one after the other."""
    spots = [m.span() for m in re.finditer(r"\w+", text)]
    body = [text[s:e].lower() for s, e in spots]
    pairs, found = list(zip(body, body[1:])), []
    for name, notice in notices:
        own = [w.lower() for w in re.findall(r"\w+", notice)]
        own, n = set(zip(own, own[1:])), len(own) - 1
        for start in range(len(pairs)):
            if pairs[start] not in own:
                continue
            ends = {e for e in range(start + 1, len(pairs) + 1) if pairs[e - 1] in own and e - 1 < start + int(1.5 * n + 1e-9)}
            ends.add(min(start + n, len(pairs)))
            sets = [(set(pairs[start:e]), e) for e in ends]
            dice, end = max((2 * len(w & own) / (len(w) + len(own)), e) for w, e in sets)
            if dice >= least:
                found.append((-dice, -n, start, end, name))
    kept = []
    for dice, _, start, end, name in sorted(found):
        if all(end <= s or e <= start for s, e, _, _ in kept):
            kept.append((start, end, -dice, name))
    return [(name, dice, spots[s][0], spots[e][1]) for s, e, dice, name in sorted(kept)]


@given(words, words, words)
@settings(max_examples=150, deadline=None)
def test_licence_scan_is_the_plain_one(one, two, body):
    notices = [(n, " ".join(w)) for n, w in (("n", one), ("m", two)) if len(w) > 1]
    if notices:
        text = " ".join(body + one + body[:5] + two)
        assert licences.Scanner({n: [w] for n, w in notices}).scan(text) == plain_licences(text, sorted(notices))


def test_licence_positions_and_long_texts():
    scanner = licences.Scanner()
    text = "\u0130 text \u0130\u0130. Licensed under CC BY 4.0. end"
    assert [(n, text[s:e]) for n, _, s, e in scanner.scan(text)] == [("CC-BY-4.0", "Licensed under CC BY 4.0")]
    began = time.perf_counter()
    assert len(scanner.scan("All rights reserved. " * 20000)) == 20000
    assert time.perf_counter() - began < 10


def test_templates_of_a_folder(spark, tmp_path):
    (tmp_path / "Own-1.0.txt").write_text("Anyone may read these words\nand nobody may sell them.")
    notices = licences.read_templates(spark, str(tmp_path))
    assert [x[:2] for x in licences.Scanner(notices).scan("So: anyone may read these words and nobody may sell them!")] == [("Own-1.0", 1.0)]


# ---- pieces -----------------------------------------------------------------------------


@pytest.fixture(scope="module")
def vocabulary():
    return sentencepieces.Vocabulary.load()


def _encode(encoder, texts):
    ids, counts = encoder.encode_batch(texts)
    ends = np.cumsum(counts)
    return [ids[e - c : e].tolist() for e, c in zip(ends, counts)]


def test_round_trip(vocabulary):
    encoder = sentencepieces.Encoder(vocabulary)
    texts = ["", " ", "  two  spaces ", "a▁b ▁", "▁", "line\nbreak \n\n x", "\tétÉ 漢字 🙂 \x00 end.", "a" * 3000, "x.y,z. , .", "Straße, groß."]
    assert [sentencepieces.decode(x, vocabulary) for x in _encode(encoder, texts)] == texts


@given(st.lists(st.text(max_size=60), max_size=6))
@settings(max_examples=60, deadline=None)
def test_round_trip_of_any_text(vocabulary, texts):
    encoder = sentencepieces.Encoder(vocabulary)
    texts = [t.encode("utf-8", "ignore").decode() for t in texts]
    assert [sentencepieces.decode(x, vocabulary) for x in _encode(encoder, texts)] == texts


def _varint(data, at):
    value = shift = 0
    while True:
        byte = data[at]
        value |= (byte & 127) << shift
        at, shift = at + 1, shift + 7
        if byte < 128:
            return value, at


def _fields(data):
    at = 0
    while at < len(data):
        start = at
        key, at = _varint(data, at)
        if key & 7 == 0:
            value, at = _varint(data, at)
        elif key & 7 == 5:
            value, at = data[at : at + 4], at + 4
        elif key & 7 == 1:
            value, at = data[at : at + 8], at + 8
        else:
            size, at = _varint(data, at)
            value, at = data[at : at + size], at + size
        yield key >> 3, data[start:at], value


def _message(number, body):
    size, out = len(body), b""
    while size > 127:
        out, size = out + bytes([size & 127 | 128]), size >> 7
    return bytes([number << 3 | 2]) + out + bytes([size]) + body


def unigram_model(vocabulary):
    """The library's own encoder over the same pieces and scores, as a unigram model."""
    import sentencepiece

    out, number = b"", 0
    for field, raw, value in _fields(open(sentencepieces.MODEL, "rb").read()):
        if field == 1:
            body = b"".join(r for f, r, _ in _fields(value) if f != 2)
            body += b"\x15" + struct.pack("<f", vocabulary.scores[number])
            out, number = out + _message(1, body), number + 1
        elif field == 2:
            body = b"".join(r for f, r, _ in _fields(value) if f != 3) + b"\x18\x01"
            out += _message(2, body)
        else:
            out += raw
    return sentencepiece.SentencePieceProcessor(model_proto=out)


def test_viterbi_is_the_library_s(vocabulary):
    import duckdb

    model = unigram_model(vocabulary)
    encoder = sentencepieces.Encoder(vocabulary)
    texts = [t for (t,) in duckdb.sql("SELECT text FROM '/root/testdata/sf0.001/documents.parquet'").fetchall()]
    ours, theirs = _encode(encoder, texts), model.encode(texts)
    # Ours is the maximum in double precision; the library adds in single precision, so where
    # two segmentations are that close it may take the other.
    for a, b in zip(ours, theirs):
        best, other = vocabulary.scores[a].sum(), vocabulary.scores[b].sum()
        assert a == b or other - 1e-9 * abs(best) <= best <= other + 1e-5 * abs(best)
    assert sum(a == b for a, b in zip(ours, theirs)) >= 0.9 * len(texts)


def test_cache_may_be_cleared(vocabulary, monkeypatch):
    monkeypatch.setattr(sentencepieces, "CACHE_UNITS", 3)
    monkeypatch.setattr(sentencepieces, "KEPT_UNITS", 2)
    encoder = sentencepieces.Encoder(vocabulary)
    for text in ("one two three four five", "six seven", "one two"):
        assert sentencepieces.decode(_encode(encoder, [text])[0], vocabulary) == text


# ---- benchmark search -------------------------------------------------------------------


def plain_hits(text, items, size):
    w = [x.decode() for x in decontam.words_of(text)]
    hit, ids = set(), set()
    for item, body in items:
        b = [x.decode() for x in decontam.words_of(body)]
        n = min(size, len(b))
        for i in range(len(b) - n + 1 if n else 0):
            for j in range(len(w) - n + 1):
                if w[j : j + n] == b[i : i + n]:
                    hit |= set(range(j, j + n))
                    ids.add(item)
    return len(w), len(hit), sorted(ids)


@given(st.lists(words, max_size=5), st.lists(words, min_size=1, max_size=5))
@settings(max_examples=80, deadline=None)
def test_search_is_the_plain_one(bodies, texts):
    items = [(str(i), " ".join(b)) for i, b in enumerate(bodies)]
    docs = ["; ".join(t).title() for t in texts] + [None, ""]
    for size in (3, 10):
        sets = [decontam.Patterns(items, size)]
        want = [(n, hit, len(ids), ids) for n, hit, ids in (plain_hits(t, items, size) for t in docs)]
        assert decontam.judge_texts(docs, sets) == want
        split = [decontam.Patterns(items[:2], size), decontam.Patterns(items[2:], size)]
        assert decontam.judge_texts(docs, split) == want
        spans = decontam.hit_spans(docs, sets[0])
        assert {i: (sum(e - s for s, e in own), sorted(ids)) for i, (own, ids) in spans.items()} == {
            i: (hit, ids) for i, (_, hit, _, ids) in enumerate(want) if hit
        }


def test_search_across_lanes_and_letters():
    item = "Eins zwei drei vier fünf sechs sieben acht neun zehn elf"
    filler = "anders " * 2000
    text = filler + item.upper().replace("Ü", "ü") + " " + filler + "EINS zwei"
    assert decontam.judge_texts([text], [decontam.Patterns([("b", item)])]) == [(4013, 11, 1, ["b"])]
    assert decontam.judge_texts([text], [decontam.Patterns([(None, item)])]) == [(4013, 11, 1, [])]


# ---- weak labels ---------------------------------------------------------------------------


def test_expectation_maximisation_finds_the_accuracies(spark):
    rng = np.random.default_rng(5)
    size, accuracy = len(weakquality.labellers()), np.array([0.95, 0.9, 0.85, 0.8, 0.75, 0.9, 0.7, 0.85, 0.8])
    counts = {}
    for good in rng.random(20000) < 0.7:
        right = rng.random(size) < accuracy
        quiet = rng.random(size) < 0.3
        pattern = "".join("-" if q else "g" if r == good else "b" for q, r in zip(quiet, right))
        counts[pattern] = counts.get(pattern, 0) + 1
    model = weakquality.fit_labels(counts)
    assert abs(model.prior - 0.7) < 0.05
    assert np.abs(model.accuracies() - accuracy).max() < 0.06
    assert weakquality.fit_labels({}).posterior == {}


def test_features_of_odd_texts():
    for text in (None, "", "a", "!" * 5000, "word " * 4000):
        at, x = weakquality.features(text)
        assert len(at) == len(x) and np.isfinite(x).all() and at.max() < weakquality.BUCKETS
