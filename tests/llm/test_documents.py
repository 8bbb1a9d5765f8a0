"""Operators on documents against brute force, with nulls, empty and long texts, ties and repeated rows."""

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from claimfold.llm import minhash, mixing, ppm, quality, substring

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n_words string, id string"


def lower(s):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(5)
    vocab = ["".join(rng.choice("aeiouéß日rstln") for _ in range(rng.randint(1, 7))) for _ in range(400)]
    passage = [rng.choice(vocab) for _ in range(60)]
    base = [rng.choice(vocab) for _ in range(120)]
    texts = [None, "", "   \n\t ", "one", "One two three", "x " * 3000, "a b c d", "a b c d", "a|b # $ %\n\nline\nline\nline"]
    for _ in range(40):
        own = [rng.choice(vocab) for _ in range(rng.randint(5, 200))]
        if rng.random() < 0.5:
            cut = rng.randint(0, len(own))
            own[cut:cut] = passage[rng.randint(0, 20) : rng.randint(35, 60)]
        texts.append(rng.choice([" ", "\n", "  "]).join(own))
    for _ in range(30):
        near = list(base)
        for _ in range(rng.randint(0, 3)):
            near[rng.randrange(len(near))] = rng.choice(vocab)
        texts.append(" ".join(near))
    texts += [" ".join(base).upper()] * 4
    sources = ["a", "b", None, "a"]
    out = [(i * 3, t, "en", sources[i % 4], None, "clash", "clash") for i, t in enumerate(texts)]
    return out + [out[20], out[20], (None, texts[20], None, None, None, None, None), (None, None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


def shingles(text):
    w = WORD.findall(lower(text or ""))
    return set() if not w else {tuple(w)} if len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def test_near_duplicates(docs, rows, nothing):
    known = [(r[0], shingles(r[1])) for r in rows if r[0] is not None]
    up = {i: i for i, _ in known}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for k, (i, a) in enumerate(known):
        for j, b in known[k + 1 :]:
            if a and b and 100 * len(a & b) >= 85 * len(a | b):
                x, y = sorted((root(i), root(j)))
                up[y] = x
    got = minhash.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    size = dict(known)
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None and r["kept"]
            continue
        assert r["n_shingles"] == len(size[r["doc_id"]])
        assert r["component_id"] == root(r["doc_id"])
        assert r["kept"] == (r["doc_id"] == r["component_id"])
    assert minhash.near_duplicates(nothing).count() == 0


def test_blocks_of_large_groups(spark, monkeypatch):
    """A group beyond the block size gives the same components."""
    monkeypatch.setattr(minhash, "BLOCK_LEAST", 8)
    base = [f"w{i}" for i in range(100)]
    rows = [(k, " ".join([*base[:10], f"v{k}", *base[10:]])) for k in range(60)]
    got = minhash.near_duplicates(spark.createDataFrame([*rows, (99, "alone here")], "doc_id long, text string")).collect()
    assert {r["component_id"] for r in got if r["doc_id"] != 99} == {0}


def removed(rows, window=13):
    first = {}
    for i, t in sorted(((r[0], r[1]) for r in rows if r[0] is not None), key=lambda r: r[0]):
        w = WORD.findall(t or "")
        for s in range(len(w) - window + 1):
            first.setdefault(tuple(w[s : s + window]), i)
    out = []
    for r in rows:
        w = WORD.findall(r[1] or "")
        gone = set()
        for s in range(len(w) - window + 1):
            if r[0] is not None and first[tuple(w[s : s + window])] < r[0]:
                gone |= set(range(s, s + window))
        out.append((r[0], len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone)))
    return sorted(out, key=str)


def test_substring(docs, rows, nothing, monkeypatch):
    monkeypatch.setattr(substring, "BATCH_BYTES", 3000)
    monkeypatch.setattr(substring, "BUCKET_BYTES", 4000)
    got = substring.remove_repeats(docs, keep=("lang", "n_words")).collect()
    assert sorted(((r[0], r[1], r[2], r[3]) for r in got), key=str) == removed(rows)
    assert {r[5] for r in got} == {"clash", None}
    assert substring.remove_repeats(nothing).count() == 0
    with pytest.raises(ValueError):
        substring.remove_repeats(docs, window=12)


def test_substring_hot_passage(spark, monkeypatch):
    """A passage in every text asks its bucket once a batch: for its keys, and for its windows."""
    passage = " ".join(f"p{k}" for k in range(30))
    rows = [(i, f"a{i} b{i} {passage} c{i}") for i in range(200)]
    one = pa.table({"id": [r[0] for r in rows], "text": [r[1] for r in rows], "b": pa.array([0] * 200, pa.int32()), "copy_of": pa.array([None] * 200, pa.int64())})
    asked = substring._anchor_requests(1, 7)(one)
    assert sum(len(k) // 4 for k in asked.column("key").to_pylist()) == 30 - 6 + 200 * 3
    windows = substring._window_requests(1, 7, 13)(one, substring._anchor_answers(asked)).to_pylist()
    home = [substring._unpack(r["payload"], np.int32, np.uint32) for r in windows if r["bucket"] == -1]
    sent = [substring._unpack(r["payload"], np.int32, np.int64, np.int32, np.uint32, np.uint32)[4] for r in windows if r["bucket"] >= 0]
    assert sum(len(place) for _, place in home) == 199 * (30 - 12)
    assert sum(map(len, sent)) <= 18 + 200 * 3
    monkeypatch.setattr(substring, "BATCH_BYTES", 3000)
    got = substring.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(map(tuple, got), key=str) == removed(rows)


def measures(text):
    t = text or ""
    w = WORD.findall(t)
    lines = [x for x in t.split("\n") if WORD.search(x)]
    seen, cover = {}, set()
    for i in range(len(w) - 2):
        seen.setdefault(tuple(w[i : i + 3]), []).append(i)
    for at in seen.values():
        if len(at) > 1:
            cover |= {i + k for i in at for k in range(3)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover), len(lines)


def test_quality(docs, rows, nothing):
    got = quality.apply_policy(quality.ledger(docs)).collect()
    want = sorted((str(r[0]), *measures(r[1])) for r in rows)
    assert sorted((str(r["doc_id"]), *(r[m] for m in quality.MEASURES)) for r in got) == want
    for r in got:
        n, chars, sym, dup, rep, lines = (r[m] for m in quality.MEASURES)
        fails = [n < 50, 100 * rep > 50 * n, 10 * sym > n, 2 * dup > lines, chars > 15 * n, n == 0, n > 1000000]
        assert r["failed"] == sum(1 << i for i, f in enumerate(fails) if f)
        assert r["kept"] == (not any(fails[:5]))
    kept = quality.screen(docs)
    assert kept.columns == docs.columns and kept.count() == sum(r["kept"] for r in got)
    assert quality.screen(nothing).count() == 0
    alone = {r["rule"]: r["failed_alone"] for r in quality.ablation(quality.ledger(docs)).collect()}
    assert alone["few_words"] == sum(r["failed"] & quality.DEFAULT.mask == 1 for r in got)


def test_mixing(docs, rows, nothing):
    got = mixing.mix(docs).collect()
    assert sorted(map(str, ((r["doc_id"], r["taken"]) for r in got))) == sorted(map(str, ((r["doc_id"], r["taken"]) for r in mixing.mix(docs).collect())))
    size = {}
    for r in rows:
        size[r[3]] = size.get(r[3], 0) + len(WORD.findall(r[1] or ""))
    order = sorted(size, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    want, free, left = {}, set(order), float(sum(size.values()))
    while free:
        level = left / sum(weight[s] for s in free)
        capped = {s for s in free if level * weight[s] > 3 * size[s]}
        if not capped:
            want |= {s: level * weight[s] for s in free}
            break
        want |= {s: 3.0 * size[s] for s in capped}
        left -= sum(3 * size[s] for s in capped)
        free -= capped
    for r in got:
        assert r["source_size"] == size[r["source"]] and abs(r["target"] - want[r["source"]]) < 1e-6
        assert r["taken"] == r["copies"] * r["size"] <= 3 * r["size"]
        share = want[r["source"]] / size[r["source"]] if size[r["source"]] else 0
        assert not r["size"] or int(share) <= r["copies"] <= int(share) + 1
    for s in order:
        n = sum(r["copies"] for r in got if r["source"] == s and r["size"])
        assert abs(n - want[s] / size[s] * sum(1 for r in got if r["source"] == s and r["size"])) <= 1
    sampled = mixing.sample(docs)
    assert sampled.columns == docs.columns and sampled.count() == sum(r["copies"] for r in got)
    assert mixing.mix(nothing).count() == 0


def test_targets_stop_at_three_times(spark):
    got = {r["source"]: r["target"] for r in mixing.targets(spark.createDataFrame([("a", 10), ("b", 1000), (None, 0)], "source string, source_size long")).collect()}
    assert got == {"a": 30.0, "b": 980.0, None: 0.0}


def test_ppm(docs, rows, nothing, monkeypatch):
    monkeypatch.setattr(ppm, "BATCH_BYTES", 4000)
    monkeypatch.setattr(ppm, "BUCKET_BYTES", 500)
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2
    is_held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 7 == 2
    for escape in ("a", "c", "d"):
        got = ppm.score_documents(docs, held, escape=escape).collect()
        trie = ppm.Trie(ppm.ORDER, escape)
        for r in rows:
            if not is_held(r[0]):
                trie.learn(r[1])
        want = sorted((str(r[0]), round(trie.score(r[1]), 6)) for r in rows)
        assert [(a, pytest.approx(b, abs=1e-5)) for a, b in want] == sorted((str(r["doc_id"]), round(r["score"], 6)) for r in got)
    assert ppm.score_documents(nothing, held).count() == 0
    context = bytes([ppm.PAD]) * ppm.ORDER
    assert abs(sum(10 ** trie.log10(context, s) for s in range(ppm.SYMBOLS)) - 1) < 1e-9
    adaptive = {r["doc_id"]: r["score"] for r in ppm.adaptive_scores(docs.where("doc_id in (9, 15)")).collect()}
    assert adaptive[15] / 6000 > adaptive[9] / 3  # a long repetition costs little a byte


def test_digest_of_nothing(docs):
    assert hashlib.sha256(b"").hexdigest() in {r[0] for r in substring.remove_repeats(docs).select(F.sha2("kept_text", 256)).collect()}
