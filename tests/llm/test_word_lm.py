import random
from collections import Counter
from math import log2

import numpy as np
import pytest

from bedvoids.llm import queries as Q
from bedvoids.llm import word_lm as W
from bedvoids.llm.store import table

SCHEMA = "doc_id long, text string"


def brute(rows, ids):
    split = [[None, *(t or "").split(), 0] if (t or "").split() else [] for _, t in rows]
    counts = []
    for which in (lambda d: d in ids, lambda d: True):
        c = Counter()
        for (d, _), s in zip(rows, split, strict=True):
            if which(d):
                c[()] += max(0, len(s) - 1)
                for n in range(1, W.ORDER + 1):
                    c.update(tuple(s[i : i + n]) for i in range(len(s) - n + 1))
        counts.append(c)
    if not counts[0][()]:
        counts[0] = counts[1]
    t, b = counts

    def p(c, s, i):
        share = b[(s[i],)] / b[()]
        out = (1 - W.MIX) * c[(s[i],)] / c[()] + W.MIX * share if c is t else share
        for n in range(1, min(W.ORDER - 1, i) + 1):
            out = (c[tuple(s[i - n : i + 1])] + W.STRENGTH * out) / (c[tuple(s[i - n : i])] + W.STRENGTH)
        return out

    bits = lambda c, s: -sum(log2(p(c, s, i)) for i in range(1, len(s))) / (len(s) - 1)
    return sorted((d, max(0, len(s) - 2), *((bits(t, s), bits(b, s)) if s else (None, None))) for (d, _), s in zip(rows, split, strict=True))


@pytest.mark.parametrize("ids", [{0, 3, 8, 40}, {99}])
def test_against_brute_force(spark, ids):
    r = random.Random(5)
    words = ["a", "A", "bé", "10", "11", "x.", "日本", "the", "of"]
    rows = [(i, " ".join(r.choice(words) for _ in range(r.randint(1, 40)))) for i in range(60)]
    rows += [(60, None), (61, ""), (62, " \n "), (3, rows[3][1]), (63, "one"), (8, rows[9][1])]
    df = spark.createDataFrame(rows, SCHEMA).repartition(5)
    got = sorted(((x.doc_id, x.n_tokens, x.target_bits, x.background_bits, x.score) for x in W.scores(df, df.sparkSession.createDataFrame([(i,) for i in ids], "doc_id long")).collect()), key=lambda x: (x[:2], x[3] or 0))
    want = sorted(brute(rows, ids), key=lambda x: (x[:2], x[3] or 0))
    assert [x[:2] for x in got] == [x[:2] for x in want]
    for x, y in zip(got, want, strict=True):
        assert x[2:4] == (None, None) if y[2] is None else x[2:4] == pytest.approx(y[2:])
        assert x[4] is None if y[2] is None else x[4] == pytest.approx(y[2] - y[3], abs=1e-9)
    assert W.scores(df.where("doc_id < 0"), df).count() == 0


@pytest.mark.parametrize("kind", ["in the year {} they met", "{} stood on the hill", "{} 東京"])
def test_query_knows_words_that_share_symbols(spark, kind, monkeypatch):
    """Numbers, case and letters beyond ASCII, which the forty symbols fold into one."""
    one, other = {"i": ("1815", "1942"), "{} s": ("PARIS", "paris"), "{} 東": ("é", "á")}[next(k for k in ("i", "{} s", "{} 東") if kind.startswith(k))]
    rows = [(i, kind.format(one if i % 2 else other)) for i in range(20)]
    tables = {"documents": spark.createDataFrame(rows, SCHEMA), "labels": spark.createDataFrame([(i, 1 if i % 2 else 0) for i in range(10)], "doc_id long, quality int")}
    monkeypatch.setattr(Q, "table", lambda s, d, name: tables[name])
    got = {x.doc_id: x.score for x in Q.op10_lm_score(spark, "").collect()}
    assert got[11] < got[10] - 0.1


def test_target_language_scores_lower(spark):
    d = table(spark, "/root/testdata/sf0.01", "documents")
    got = W.scores(d, d.where("lang = 'fr' and doc_id % 2 = 0")).join(d.select("doc_id", "lang"), "doc_id").where("doc_id % 2 = 1 and n_tokens > 30").collect()
    fr, other = [r.score for r in got if r.lang == "fr"], [r.score for r in got if r.lang != "fr"]
    assert np.median(fr) < np.median(other) - 0.1
