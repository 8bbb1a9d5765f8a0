"""Tokenizer, notices, toxicity, pages and recordings."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from claimfold.llm import bpe, html, license, queries, toxicity

P = pytest.importorskip("public_tokenizers")
tokenizers = pytest.importorskip("tokenizers")


def texts():
    rng = random.Random(3)
    out = ["", "a<|endoftext|>b  c", "  \n\n x\t\ty'll don't I'VE 12345 ¼ ½ x²", "日本語 テキスト 🙂🙂 émile", "   á", "%" * 900, " " * 500 + "a", "-_" * 400, "\x00\x01\x85 \u0085x", "aaaa" * 120]
    out += ["".join(rng.choice("abcdefghij \nétion'sXYZ0123,.!?") for _ in range(200)) for _ in range(100)]
    return out + ["".join(rng.choice("theraninousioxy") for _ in range(50)) for _ in range(300)]


def test_bpe_equals_library(spark):
    path = queries.vocabulary_path()
    lib = tokenizers.Tokenizer.from_file(path)
    all_ = texts()
    rows = [(i, t) for i, t in enumerate(all_)] + [(-1, None)]
    got = {r["doc_id"]: r for r in bpe.encode_and_decode(spark.createDataFrame(rows, "doc_id long, text string"), path).collect()}
    for i, e in enumerate(lib.encode_batch(all_, add_special_tokens=False)):
        assert got[i]["ids"] == ",".join(map(str, e.ids)) and got[i]["n_tokens"] == len(e.ids)
        assert got[i]["decoded"] == lib.decode(e.ids, skip_special_tokens=False)
    assert (got[-1]["n_tokens"], got[-1]["ids"], got[-1]["decoded"]) == (0, "", "")
    c = bpe.codec(path)
    assert all(c.encode(t) == lib.encode(t, add_special_tokens=False).ids for t in all_[:20])
    pairs = [(a, b) for a in range(250, 290) for b in range(250, 290)]
    many = c.fits_many(np.array([a for a, _ in pairs]), np.array([b for _, b in pairs]))
    assert many.tolist() == [c.fits(a, b) for a, b in pairs]


def test_notices(spark):
    rows = [(1, "Licensed under CC BY-NC 4.0. All rights reserved."), (2, "Relesed under teh MIT License"), (3, "licensed under the Apache Licence, Version 2.0"), (4, None), (5, ""), (6, "nothing of the kind"), (7, "cc by cc by"), (8, "GNU General Public License")]
    got = {r["doc_id"]: r for r in license.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1]["base_labels"] == "cc-by,reserved" and got[1]["labels"] == "cc-by,cc-by-nc,reserved" and (got[1]["first_word"], got[1]["last_word"]) == (2, 7)
    assert got[2]["labels"] == "mit" and got[2]["n_base"] == 0 and 0 < got[2]["score"] < 1 and got[2]["first_word"] is None
    assert got[3]["labels"] == "apache-2.0" and [(s["first"], s["last"]) for s in got[3]["spans"]] == [(0, 7)]
    assert got[4]["n_words"] == got[5]["n_words"] == 0 and got[6]["labels"] == "" and got[6]["score"] == 0
    assert got[7]["n_base"] == 2 and got[8]["base_labels"] == "gpl"


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a):
        row = _step(row, i, x, b)
    return row[-1]


def _step(row, i, x, b):
    out = [i + 1]
    for j, y in enumerate(b):
        out.append(min(row[j + 1] + 1, out[j] + 1, row[j] + (x != y)))
    return out


def test_automaton_equals_edit_distance():
    rng = random.Random(1)
    terms = ["moron", "idiots", "abc", "motor", "scummy"]
    lex = toxicity.Lexicon(terms, ["vequ"])
    words = terms + ["vequ", "vequabc", "vequ1", "oron", "mroon", "mooron", "idiot", "zzz"]
    words += ["".join(rng.choice("morniditsabcequv") for _ in range(rng.randint(1, 7))) for _ in range(3000)]
    joined, points, start, end, _ = toxicity.spans([" ".join(words)])
    kinds = lex.match(points, start, end)
    for w, k in zip(words, kinds.tolist(), strict=True):
        want = 1 if w in terms else 2 if w.startswith("vequ") else 3 if any(len(t) >= 5 and distance(w, t) <= 1 for t in terms) else 0
        assert k == want, (w, k, want)


def test_toxicity_learns(spark):
    rng = random.Random(2)
    plain = ["tree", "house", "river", "cloud", "stone", "walk", "green", "fast", "little", "moon"]
    rows, labels = [], []
    for i in range(400):
        w = [rng.choice(plain) + rng.choice("abcdefgh") for _ in range(30)]
        bad = i % 5 == 0
        if bad:
            w[rng.randrange(1, 29)] = rng.choice(["grumblik", "vortexian"])
        rows.append((i, " ".join(w)))
        labels.append((i, int(bad)))
    rows += [(1000, "you grumblic one"), (1001, "treea houseb"), (1002, None), (1003, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    model = toxicity.fit(docs, spark.createDataFrame(labels, "doc_id long, toxic int"), F.col("id") % 4 != 2)
    assert set(model.lexicon.terms) == {"grumblik", "vortexian"}
    got = {r["doc_id"]: r for r in toxicity.score_documents(docs, model).collect()}
    assert all(got[i]["predicted"] == y for i, y in labels) and got[1000]["predicted"] == 1
    assert got[1001]["predicted"] == got[1002]["predicted"] == got[1003]["predicted"] == 0
    nobody = toxicity.fit(docs, spark.createDataFrame([], "doc_id long, toxic int"), F.lit(True))
    assert nobody is None and toxicity.score_documents(docs, nobody).where("score > 0").count() == 0


PAGE = """<!DOCTYPE html><html><head><title>T &amp; U</title><style>p{}</style><script>var a="</p>";</script></head><body>
<nav><ul><li><a href="/a">Home</a></li><li><a href="/b">More</a></li></ul></nav><div class="cookie-notice">We use cookies here and there</div>
<%s><h1>Head&nbsp;line</h1><p>First   paragraph of &lt;text&gt; with many words in it to score.<br><p>Second <b>bold</b>
part.</p><div class="ad">Buy now, buy soon, buy ever more of it</div><ul><li>item one of a list</li></ul><p>End.</p></%s>
<div id="comments"><p>I liked reading this very much indeed</p><div><p>nested reply to it</p></div></div>
<aside>Related things to see</aside><form><p>Your mail please</p></form><footer>&copy; somebody, all of it</footer></body></html>"""
TEXT = "Head line\nFirst paragraph of <text> with many words in it to score.\nSecond bold part.\nitem one of a list\nEnd."


@pytest.mark.parametrize("tag", ["article", "main", "div"])
def test_main_text(tag):
    w = html.Weights()
    w.tags |= {t: -0.05 for t in ("p", "h1", "b", "br", "ul", "li")}
    assert html.extract(PAGE % (tag, tag), w) == TEXT


def test_main_text_edges(spark):
    rows = [(1, "u", None), (2, "u", ""), (3, "u", "plain words only"), (4, None, "<p>" * 50), (5, "u", "<p>unclosed <b>bold"), (6, "u", "a < b and c > d")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: r for r in html.main_text(pages, html.fit(pages), keep=("url",)).collect()}
    assert got[1]["text"] == got[2]["text"] == got[4]["text"] == "" and got[1]["n_chars"] == 0
    assert got[3]["text"] == "plain words only" and got[5]["text"] == "unclosed bold" and got[6]["text"] == "a < b and c > d"


def test_best_region_by_brute_force():
    rng = random.Random(4)
    w = html.Weights(tags={"p": -0.3, "li": -2.0})
    for _ in range(200):
        parts = [html.Item(tag=rng.choice(["p", "li", "x"])) if rng.random() < 0.5 else html.Item(text="w", words=rng.randint(1, 4), linked=rng.random() < 0.3) for _ in range(12)]
        score = [w.tags.get(p.tag, w.other_tag) if p.tag else p.words * (w.linked if p.linked else w.word) for p in parts]
        best = max([0.0, *(sum(score[a:b]) for a in range(12) for b in range(a + 1, 13))])
        a, b = html.region(parts, w)
        assert math.isclose(sum(score[a:b]), best, abs_tol=1e-9)


def test_toxicity_does_not_depend_on_partitions(spark):
    """Terms near the threshold, repeated ids and rows, clashing columns, null and long texts."""
    rng = random.Random(9)
    rows, labels = [], []
    for i in range(300):
        w = ["".join(rng.choice("abcdefgh") for _ in range(4)) for _ in range(rng.randint(1, 6))]
        if i % 6 == 0:
            w.insert(rng.randrange(len(w) + 1), rng.choice(["grumblik", "vortexian", "zzurk"]))
        rows.append((i, " ".join(w), "x", 0.5))
        labels.append((i, int(i % 6 == 0)))
    rows += [rows[6], (6, "another text of one id", "x", 0.1), (900, None, None, None), (901, "grumblik " * 50_000, "y", 1.0), (None, "vortexian", "z", None)]
    labels += [(6, 0), (12, None), (None, 1)]
    known = spark.createDataFrame(labels, "doc_id long, toxic int")
    seen = set()
    for parts in (1, 3, 7):
        docs = spark.createDataFrame(rows, "doc_id long, text string, label string, score double").repartition(parts)
        model = toxicity.fit(docs, known, F.lit(True))
        got = sorted((str(r["doc_id"]), round(r["score"], 9), r["predicted"]) for r in toxicity.score_documents(docs, model).collect())
        assert len(got) == len(rows)
        seen.add((tuple(model.lexicon.terms), tuple(model.lexicon.stems), tuple(got)))
    assert len(seen) == 1
    assert toxicity.score_documents(docs.where("false"), model).count() == 0


def test_tokens_of_edges(spark):
    path = queries.vocabulary_path()
    lib = tokenizers.Tokenizer.from_file(path)
    long = "abc é" * 60_000
    rows = [(1, long, "a", 1), (1, long, "a", 1), (2, None, "b", 2), (None, "x y", None, None), (3, "a" * 30_000, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids string, n_tokens int")
    got = bpe.encode_and_decode(docs, path).collect()
    want = sorted((str(r[0]), ",".join(map(str, lib.encode(r[1] or "", add_special_tokens=False).ids))) for r in rows)
    assert sorted((str(r["doc_id"]), r["ids"]) for r in got) == want
    assert bpe.encode_and_decode(docs.where("false"), path).count() == 0
