"""Notices against edit distances of every place, and the edges."""

import random

import pyarrow as pa
from pyspark.sql import functions as F

from claimfold.llm import license

COMPILED = license.compile_notices()


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, start=1):
        new = [i]
        for j, y in enumerate(b, start=1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def brute(text):
    words = text.split()
    found = set()
    for (marked, label), notice in zip(license.NOTICES, COMPILED, strict=True):
        want = marked.split()
        for s in range(len(words) - len(want) + 1):
            total = 0
            for w, have in zip(want, words[s : s + len(want)], strict=True):
                d = distance(w.rstrip("!"), have)
                known = {x.rstrip("!") for x in want}
                if d > license.word_errors(w) or (have in license.CONFUSED and have not in known):
                    break
                total += d
            else:
                if total <= notice.errors:
                    found.add((0, s, s + len(want) - 1, label, total, len(notice.words)))
    return sorted(license.best_places(found))


def spoil(rng, word):
    at = rng.randrange(len(word) + 1)
    kind = rng.random()
    if kind < 0.4 and len(word) > 1:
        return word[:at] + word[at + 1 :]
    letter = rng.choice("abcdeilnstu0é")
    return word[:at] + letter + word[at:] if kind < 0.7 else word[:at] + letter + word[at + 1 :]


def test_every_place():
    rng = random.Random(8)
    filler = "the license under version 2 0 public general cc by nc licensed rights all source free gnu mit".split()
    hits = 0
    for _ in range(600):
        words = []
        for _ in range(3):
            words += [rng.choice(filler) for _ in range(rng.randint(0, 6))]
            notice = [w.rstrip("!") for w in rng.choice(license.NOTICES)[0].split()]
            for _ in range(rng.randint(0, 4)):
                k = rng.randrange(len(notice))
                notice[k] = spoil(rng, notice[k]) or "x"
            if rng.random() < 0.2:
                notice[rng.randrange(len(notice))] = rng.choice(filler)
            words += notice
        text = " ".join(words)
        w, found = license.find_notices(pa.array([text]), COMPILED)
        assert sorted(found) == brute(text), text
        hits += len(found)
    assert hits > 500


def test_other_licences_get_no_wrong_label():
    for text, allowed in (
        ("released under the BSD license", {"bsd"}), ("licensed under the GPL license", set()), ("licensed under the isc license", {"isc"}), ("licensed under CC BY 4.0", set()),
        ("Apache License version 1.1", set()), ("all rights preserved", set()), ("licensed under CC BY-SA 4.0", {"cc-by-sa"}), ("licensed under the Apache License, version 1.1", {"apache-1.1"}),
    ):
        _, found = license.find_notices(pa.array([text]), COMPILED)
        assert {f[3] for f in found} == allowed, text


def test_edges(spark):
    text = "Released under the MIT license. " * 3000
    rows = [(1, text, "x", "y"), (1, text, "x", "y"), (2, None, None, None), (3, "", "a", "b"), (None, "All rights reserved", None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, labels string, n_words string")
    got = license.scan(docs).withColumn("spans", F.size("spans")).collect()
    assert len(got) == 5
    one = [r for r in got if r["doc_id"] == 1]
    assert one[0] == one[1] and one[0]["spans"] == 3000 and one[0]["labels"] == "mit" and one[0]["n_base"] == 0
    assert [r["labels"] for r in got if r["doc_id"] is None] == ["reserved"]
    assert all(r["n_words"] == 0 and r["score"] == 0 for r in got if r["doc_id"] in (2, 3))
    assert license.scan(docs.where("false")).count() == 0


def test_places_that_overlap():
    found = [(0, 0, 5, "a", 2, 30), (0, 3, 9, "b", 1, 30), (0, 9, 12, "c", 1, 20), (0, 13, 15, "d", 0, 20), (0, 6, 8, "e", 1, 10)]
    assert [p[3] for p in license.best_places(found)] == ["b", "d"]
