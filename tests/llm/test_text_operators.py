import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from bedvoids.llm import decontaminate as D
from bedvoids.llm import html_text, language, toxicity
from bedvoids.llm import texthash as H
from bedvoids.llm.store import table

DOCS = "doc_id long, text string, lang string, source string, label string, held_out int, score string"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, g, "s", "x", 3, "y") for i, t, g in rows], DOCS)


# decontamination
def shingles(words, k):
    return [tuple(words[i : i + k]) for i in range(len(words) - k + 1)]


def best_window(text, item, k=5):
    from collections import Counter

    words = lambda t: re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    a, b = words(text), words(item)
    k = min(k, len(b))
    if not k:
        return 0
    s, t = shingles(a, k), shingles(b, k)
    n, best = min(len(s), len(t)), 0
    for i in range(len(s) - n + 1):
        p, q = Counter(s[i : i + n]), Counter(t)
        high = sum((p | q).values())
        best = max(best, sum((p & q).values()) / high if high else 0)
    return best


def test_windows_against_brute_force(spark):
    import random

    r = random.Random(3)
    word = lambda: "w%d" % r.randint(0, 60)
    items = [(i, " ".join(word() for _ in range(r.choice([3, 12, 25, 40])))) for i in range(25)] + [(30, None), (31, ""), (32, "one"), (33, "x y x y x y x y x y x y")]
    rows = [(0, None), (1, ""), (2, "one"), (3, "x y " * 20)]
    for i in range(4, 150):
        w = [word() for _ in range(r.choice([0, 10, 60, 200]))]
        for _ in range(r.choice([0, 1, 2])):
            t = list(r.choice(items[:25])[1].split())
            for _ in range(r.choice([0, 0, 1, 1, 2, 4])):
                t[r.randrange(len(t))] = word()
            at = r.randint(0, len(w))
            w[at:at] = t if r.random() < 0.8 else t[: len(t) // 2]
        rows.append((i, " ".join(w).upper() if r.random() < 0.2 else " ".join(w)))
    df = docs(spark, [(i, t, "en") for i, t in rows]).repartition(3)
    got = {(m.doc_id, m.item_id): m.similarity for m in D.matches(df, spark.createDataFrame(items, "item_id long, text string")).collect()}
    want = {(i, j): s for i, t in rows for j, b in items if (s := best_window(t, b)) >= 0.8}
    assert got.keys() == want.keys()
    assert all(got[k] == pytest.approx(want[k]) for k in want)
    left = D.without_matches(df, spark.createDataFrame(items, "item_id long, text string"))
    assert left.columns == df.columns
    assert {x.doc_id for x in left.collect()} == {i for i, _ in rows} - {i for i, _ in want}


def test_every_fingerprint_in_the_radius_is_found():
    r = np.random.default_rng(1)
    prints = r.integers(0, 1 << 63, 300, dtype=np.uint64)
    index = D.MultiIndex(prints)
    asked = prints[r.integers(300, size=50)]
    for i in range(50):
        for bit in r.choice(64, r.integers(0, 30), replace=False):
            asked[i] ^= np.uint64(1) << np.uint64(bit)
    want = [(i, int(j)) for i, q in enumerate(asked) for j in np.flatnonzero(D.hamming(prints, np.full(300, q, np.uint64)) <= D.RADIUS)]
    assert list(zip(*(x.tolist() for x in index.near(asked)), strict=True)) == want


def test_candidates_come_from_the_index(spark, monkeypatch):
    """With a radius below 0 the index finds nothing, so nothing is confirmed."""
    df, items = docs(spark, [(1, "a b c d e f g h", "en")]), spark.createDataFrame([(1, "a b c d e f g h")], "item_id long, text string")
    assert [m.hamming for m in D.matches(df, items).collect()] == [0]
    monkeypatch.setattr(D.MultiIndex.__init__, "__defaults__", (-1,))
    assert D.matches(df, items).count() == 0


def test_rows_are_looked_at_one_by_one(spark):
    rows = [(7, "a b c d e f g h"), (7, "other words stand here and there"), (None, "a b c d e f g h x"), (None, None)]
    df = spark.createDataFrame([(*x, 1, 2) for x in rows], "doc_id long, text string, _bad int, item_id int")
    left = D.without_matches(df, spark.createDataFrame([(1, "a b c d e f g h")], "item_id long, text string"))
    assert left.columns == df.columns and {x.text for x in left.collect()} == {rows[1][1], None}


def test_nothing_to_decontaminate(spark):
    none = spark.createDataFrame([], "item_id long, text string")
    df = docs(spark, [(1, "a b c d e f", "en")])
    assert D.matches(df, none).count() == 0 and D.without_matches(df, none).count() == 1
    assert D.matches(docs(spark, []), none).count() == 0


# language
def test_languages_of_held_out_texts(spark):
    d = table(spark, "/root/testdata/sf0.01", "documents")
    got = language.identify(d).join(d.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r.lang_pred == r.lang for r in got) / len(got) > 0.98
    assert all(0 <= r.score <= 1 for r in got)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)


def test_language_edges(spark):
    rows = [(i, t, g) for i, (t, g) in enumerate([("the cat sat on the mat " * 3, "en"), ("der hund und die katze " * 3, "de")] * 12)]
    rows += [(100, None, "en"), (101, "", "de"), (102, "123 !?", "en"), (103, "x", None), (104, "Der HUND " * 30000, None), (None, "the cat", "en")]
    got = {r.doc_id: (r.lang_pred, r.score) for r in language.identify(docs(spark, rows)).collect()}
    assert [got[i] for i in (100, 101, 102)] == [("und", 0.0)] * 3
    assert got[104][0] == "de" and got[103][0] in ("de", "en") and got[None][0] == "en"
    assert language.identify(docs(spark, [])).count() == 0
    assert {r.lang_pred for r in language.identify(docs(spark, [(1, "word", None), (2, "text", None)])).collect()} == {"und"}


def test_kernels_and_regression_against_plain_formulas():
    """Sets of n-grams one by one, kernels from their sizes, and the ridge solution in the landmarks' own space."""
    import pyarrow as pa

    texts = ["the cat sat on the mat", "a dog and a cat", "der hund und die katze", "das ist ein haus", "le chat est sur la table", "une maison et un chien", "the house is old", "die katze schläft"]
    labels = ["en", "en", "de", "de", "fr", "fr", "en", "de"]
    asked = ["the dog sat", "ein hund und ein haus", "la maison", "zzz"]
    starts = np.r_[0, np.cumsum(language.PLACES)]

    def places(text):
        raw, out = text.encode(), set()
        for n, size in enumerate(language.PLACES, 1):
            for i in range(len(raw) - n + 1):
                h = int.from_bytes(raw[i : i + n], "big") * 0x9E3779B1 % (1 << 32)
                h = (h ^ h >> 15) * 0x85EBCA77 % (1 << 32)
                out.add(int(starts[n - 1]) + (h >> 16) % size)
        return out

    plain = lambda ts: language.letters(pa.array(ts, pa.string()))
    x, q = (np.concatenate([m for _, m in language.presence(plain(ts))]) for ts in (texts, asked))
    sets = [places(t) for t in plain(texts).to_pylist()]
    for row, s in zip(x, sets, strict=True):
        assert set(np.flatnonzero(row)) == s
    kernel = lambda a, b: np.array([[len(s & t) / (len(s) * len(t)) ** 0.5 for t in b] for s in a])
    model = language.Model(x, labels, landmarks=5)
    land = kernel(sets[:5], sets[:5])
    values, vectors = np.linalg.eigh(land)
    root = vectors[:, values > 1e-6 * values.max()] / np.sqrt(values[values > 1e-6 * values.max()])
    z = np.c_[kernel(sets, sets[:5]) @ root, np.ones(8)]
    y = np.array([[1.0 if g == k else -1.0 for k in ("de", "en", "fr")] for g in labels])
    w = np.array([1 / labels.count(g) for g in labels])
    w *= 8 / w.sum()
    coef = np.linalg.inv(z.T @ np.diag(w) @ z + language.RIDGE * 8 / 1000 * np.eye(z.shape[1])) @ z.T @ np.diag(w) @ y
    want = np.c_[kernel([places(t) for t in plain(asked).to_pylist()], sets[:5]) @ root, np.ones(4)] @ coef
    assert np.allclose(model.scores(q), want, atol=2e-3)


def test_copies_are_learned_from_once(spark):
    rows = [(i, "the cat sat on the mat", "en") for i in range(300)] + [(i, "der hund und die katze schlafen", "de") for i in range(300, 330)]
    df = docs(spark, rows).select("text", F.col("lang").alias("label"))
    assert language.fit(df).land.shape[0] == 2


# toxicity
def test_places_ratios_and_scores_against_plain_loops():
    """n-grams by sets, ratios by counting, scores by adding up; and weights where the penalised loss is nearly flat."""
    import zlib as z

    import pyarrow as pa

    texts = [f"you {w} idiot number {i % 7}" for i, w in enumerate(["stupid", "total", "utter"] * 8)] + [f"a {w} day in may, take {i % 5}" for i, w in enumerate(["lovely", "calm", "sunny"] * 8)]
    y = np.array([1] * 24 + [0] * 24)
    spaced = toxicity.plain(pa.array(texts, pa.string()))
    got = [set(f.tolist()) for _, f in toxicity.present(spaced)]

    def places(text):
        raw, out = text.encode(), set()
        for n in toxicity.SIZES:
            for i in range(len(raw) - n + 1):
                part = np.frombuffer(raw[i : i + n], np.uint8)
                h = toxicity.H.span(toxicity.H.prefix(part), np.array([0]), np.array([n]))[0]
                out.add(int(h) >> (64 - 18))
        return out

    assert got == [places(t) for t in spaced.to_pylist()]
    bits = []
    for s in got:
        mark = np.zeros(toxicity.PLACES, bool)
        mark[list(s)] = True
        bits.append(z.compress(np.packbits(mark).tobytes()))
    model = toxicity.Model(bits, y)
    count = {c: {} for c in (0, 1)}
    for s, c in zip(got, y, strict=True):
        for p in s:
            count[c][p] = count[c].get(p, 0) + 1
    ratio = {p: np.log((count[1].get(p, 0) + 1) / 26) - np.log((count[0].get(p, 0) + 1) / 26) for s in got for p in s}
    used = {p for p, r in ratio.items() if abs(r) >= toxicity.APART and count[0].get(p, 0) + count[1].get(p, 0) >= toxicity.LEAST}
    assert {*np.flatnonzero(model.weights).tolist()} <= used
    w = {p: float(model.weights[p]) / ratio[p] for p in used}
    grad, loss, none = dict.fromkeys(used, 0.0), 0.0, 0.0
    for s, c in zip(got, y, strict=True):
        f = sum(w[p] * ratio[p] for p in s if p in used) + model.bias
        assert model.score(np.array(sorted(s))) == pytest.approx(1 / (1 + np.exp(-f)), abs=1e-5)
        loss += np.log1p(np.exp(-f if c else f)) / 48
        none += np.log(2) / 48
        for p in s & used:
            grad[p] += ratio[p] * (1 / (1 + np.exp(-f)) - c) / 48
    assert loss + toxicity.PENALTY / 2 * sum(v * v for v in w.values()) < 0.2 * none
    assert max(abs(grad[p] + toxicity.PENALTY * w[p]) for p in used) < 0.02


def test_toxicity_of_held_out_texts(spark):
    sf = "/root/testdata/sf0.1"
    d, y = table(spark, sf, "documents"), table(spark, sf, "labels")
    got = toxicity.scores(d.join(y.select("doc_id"), "doc_id", "left_semi"), y).join(y, "doc_id").where("held_out").collect()
    wrong = sum(r.predicted != r.toxic for r in got)
    assert wrong / len(got) < 0.03  # 352 toxic texts to learn from
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)


def test_toxicity_edges(spark):
    rows = [(i, "you are an idiot and a moron" if i % 2 else "what a lovely calm day it is", "en") for i in range(60)] + [(100, None, "en"), (101, "", None), (102, "such an idiot " * 5000, "en")]
    labels = spark.createDataFrame([(i, 1, i % 2) for i in range(60)] + [(None, 1, 1), (7, 0, None)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.scores(docs(spark, rows), labels).collect()}
    assert len(got) == 63 and got[102].predicted == 1 and got[1].predicted == 1 and got[2].predicted == 0
    assert got[100].score == got[101].score
    kept = toxicity.without_toxic(docs(spark, rows), labels)
    assert kept.columns == docs(spark, []).columns and {r.doc_id for r in kept.collect()} >= {0, 2, 4} and not {1, 102} & {r.doc_id for r in kept.collect()}
    nothing = labels.where("toxic = 5")
    assert {r.score for r in toxicity.scores(docs(spark, rows), nothing).collect()} == {0.0}
    assert toxicity.scores(docs(spark, []), labels).count() == 0


# pages
def test_articles_of_given_pages(spark):
    import html as h

    pages = table(spark, "/root/testdata/sf0.01", "pages")
    got = {r.page_id: (r.text, r.n_chars) for r in html_text.extract(pages).collect()}
    for r in pages.collect():
        body = re.search(r"<article>(.*)</article>", r.html, re.S)[1]
        parts = (" ".join(h.unescape(re.sub("</?b>", "", x)).split()) for x in re.split(r"</?(?:p|h1|br|h2|ul|li)[^>]*>", body))
        want = " ".join(p for p in parts if p)
        assert got[r.page_id] == (want, len(want))


PAGE = """<html><head><title>T</title><style>p{}</style></head><body><header><a href=/>Home</a> Site name</header>
<div class="cookie-notice">We use cookies. <a href=x>More</a></div><div id=menu><ul><li><a href=1>One</a><li><a href=2>Two</a></ul></div>
<main><h1>The &lt;Title&gt; &amp; more</h1><p>First   paragraph with <a href=z>a link</a> and <b>bold</b> words in it, long enough to read.<p>Second&nbsp;one, caf&eacute; &#8364;5.
<script>if (a < b) document.write("<p>no</p>")</script><ul><li>An item of the text<li>Another item of the text</ul><blockquote>A quotation</blockquote></main>
<aside><h3>Related</h3><a href=q>Another story</a></aside><form><label>Name</label><input><button>Send</button></form>
<div class="comments"><p>Reader: I do not agree with any of this at all.</p></div><footer>Copyright</footer></body></html>"""


def test_page_of_another_layout():
    assert html_text.main_text(PAGE) == "The <Title> & more First paragraph with a link and bold words in it, long enough to read. Second one, café €5. An item of the text Another item of the text A quotation"


LONG = "One sentence with quite a number of words that make up a paragraph of the text. " * 2


@pytest.mark.parametrize("around", ['<div class="with-sidebar"><article>{}</article></div>', '<article class="has-comments">{}</article>', '<main class="search-page">{}</main>', '<form><div id="page-nav-layout"><article>{}</article></div></form>', '<div class="sidebar"><article>{}</article></div>', '<div class="content">{}</div>'])
def test_wrappers_that_name_furniture(around):
    page = "<body><nav><a href=/>Home</a></nav>" + around.format(f"<h1>Title of it</h1><p>{LONG}</p><p>Short one.</p><div class=ad>Buy this now</div><div class='comments-list'><p>{LONG}</p></div><p>{LONG}</p>") + '<div class="sidebar-left"><p>Not the text at all, whatever it says.</p></div><footer>End</footer></body>'
    assert html_text.main_text(page) == f"Title of it {LONG.strip()} Short one. {LONG.strip()}"


def test_words_and_links_of_blocks_decide():
    """Without any tag or name that says what a block is."""
    page = f"<div>Site name</div><div><a href=1>One</a> <a href=2>Two</a></div><div>{LONG}</div><div><a href=3>Three more words</a></div><div>{LONG}</div><div>Some line</div>"
    assert html_text.main_text(page) == f"{LONG.strip()} {LONG.strip()}"
    assert {html_text.FEATURES[f] for f, *_ in html_text.TREE.nodes if f >= 0} >= {"words", "links", "links_before"}


def test_page_edges(spark):
    rows = [(1, "u", None), (2, "u", ""), (3, None, "plain words only, but quite many of them so that they count as the text of this page by their number"), (4, "u", "<"), (5, "u", "<p>unclosed <b>bold"), (6, "u", "<!-- " + "x" * 100000), (7, "u", "<article><p>" + "long text " * 100000 + "</article>")]
    got = {r.page_id: r.text for r in html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == got[2] == got[6] == "" and got[3] == rows[2][2] and got[7] == ("long text " * 100000).strip()
    assert html_text.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_workers_give_back_what_a_task_took():
    def resident():
        with open("/proc/self/statm") as f:
            return int(f.read().split()[1]) * 4096

    def run(batches):
        held = []
        for batch in batches:
            held += [np.ones(12_500) for _ in range(1000)]  # 100 MB in pieces that the allocator keeps, with one in use behind them
            keep.append(np.ones(12_500))
            yield batch

    keep = []
    before = resident()
    batch = pa.RecordBatch.from_arrays([pa.array([1])], names=["x"])
    assert list(H.tidy(run)(iter([batch]))) == [batch] and resident() - before < 60e6
