"""Every stage of the pipeline, and run(), against plain Python on rows with nulls, repeats, ties and names that clash."""

import hashlib
import random

import corpus_pipeline as pipeline
import pytest
from test_documents import WORD, lower, measures, removed, shingles

from claimfold.llm import queries

tokenizers = pytest.importorskip("tokenizers")

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _again string, _mix_dup string, print string, size int"


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(12)
    vocab = ["".join(rng.choice("aeioustrnlé") for _ in range(rng.randint(3, 7))) for _ in range(900)]
    say = lambda n: [rng.choice(vocab) for _ in range(n)]
    passage, base = say(40), say(130)
    texts = [None, "", "too short", "# " * 80, " ".join(["same words again"] * 40)]
    for _ in range(30):
        words = say(rng.randint(55, 140))
        if rng.random() < 0.5:
            words[10:10] = passage[: rng.randint(13, 40)]
        texts.append(" ".join(words))
    for _ in range(12):
        near = list(base)
        for _ in range(rng.randint(0, 2)):
            near[rng.randrange(len(near))] = rng.choice(vocab)
        texts.append(" ".join(near))
    texts += [" ".join(base).upper(), " ".join(say(20_000))]
    out = [(i * 2, t, "en", ["a", "b", None][i % 3], 1, "x", "y", "z", 7) for i, t in enumerate(texts)]
    first, other = out[6], " ".join(say(90))
    out += [first, first]  # repeated rows
    out += [(14, first[1], "en", "b", 1, None, None, None, None), (14, other, "en", "b", 1, None, None, None, None)]  # one id, a copy and a text of its own
    out += [(None, first[1], None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None)]
    return [r for k, r in enumerate(out) if r[0] != 14 or k >= len(texts)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


def sort(rows):
    return sorted(map(tuple, rows), key=str)


def good(text):
    n, chars, sym, dup, rep, lines = measures(text)
    return not (n < 50 or 100 * rep > 50 * n or 10 * sym > n or 2 * dup > lines or chars > 15 * n)


def without_copies(rows):
    """One row of each (id, text); of each component of similarity 0.8 the first by id; rows without an id."""
    known = {(r[0], r[1]): r for r in rows if r[0] is not None}
    keys = list(known)
    sets = [shingles(t) for _, t in keys]
    up = list(range(len(keys)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            if a and sets[j] and 100 * len(a & sets[j]) >= 80 * len(a | sets[j]):
                up[root(i)] = root(j)
    groups = {}
    for i, k in enumerate(keys):
        groups.setdefault(root(i), []).append(k)
    return groups, known, [r for r in rows if r[0] is None]


def test_quality_rules(spark, docs, rows):
    got = pipeline.quality_rules(spark, docs, "")
    assert got.columns == docs.columns and sort(got.collect()) == sort(r for r in rows if good(r[1]))


def test_near_duplicates(spark, docs, rows):
    got = pipeline.near_duplicates(spark, docs, "")
    groups, known, none = without_copies(rows)
    assert got.columns == docs.columns
    left = got.collect()
    assert sort(r for r in left if r[0] is None) == sort(none)
    kept = {(r[0], r[1]) for r in left if r[0] is not None}
    assert len(kept) == len(left) - len(none) == len(groups)
    for group in groups.values():
        here = [k for k in group if k in kept]
        assert len(here) == 1 and here[0][0] == min(k[0] for k in group)
    assert any(len(g) > 5 for g in groups.values()) and (14, next(t for i, t in known if i == 14 and t != rows[6][1])) in kept


def test_substring_dedup(spark, docs, rows):
    got = pipeline.substring_dedup(spark, docs, "")
    assert got.columns == docs.columns
    assert sort((r[0], r[1]) for r in got.collect()) == sort((i, t) for i, _, _, t in removed(rows))
    assert all(r["n_chars"] == len(r["text"]) for r in got.collect() if r["n_chars"] is not None)


def test_source_mixing(spark, docs, rows):
    from claimfold.llm import mixing

    got = [tuple(r) for r in pipeline.source_mixing(spark, docs, "").collect()]
    copies = {}
    for r in mixing.mix(docs).collect():
        copies.setdefault((r["doc_id"], r["source"], r["size"]), []).append(r["copies"])
    assert set(got) <= set(map(tuple, rows))
    for row in set(map(tuple, rows)):
        alike = [r for r in rows if (r[0], r[3], len(WORD.findall(r[1] or ""))) == (row[0], row[3], len(WORD.findall(row[1] or "")))]
        assert sum(1 for g in got if g in set(map(tuple, alike))) == sum(copies[row[0], row[3], len(WORD.findall(row[1] or ""))])


def test_bpe_tokens(spark, docs, rows):
    assert sort(pipeline.bpe_tokens(spark, docs, "").collect()) == sort(coded((r[0], r[1]) for r in rows))


def coded(pairs):
    lib = tokenizers.Tokenizer.from_file(queries.vocabulary_path())
    lib.no_truncation()
    lib.no_padding()
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    for i, t in pairs:
        ids = lib.encode(t or "", add_special_tokens=False).ids
        yield i, len(ids), sha(",".join(map(str, ids))), sha(lib.decode(ids, skip_special_tokens=False))


def test_run(spark, docs, rows, tmp_path):
    """What run() returns is what the stages' definitions make of the table, the mix's draw taken from its own operator."""
    path = str(tmp_path)
    docs.where("doc_id is null or doc_id not in (12, 14)").write.parquet(f"{path}/documents.parquet")
    table = [r for r in rows if r[0] not in (12, 14)]
    kept = [r for r in table if good(r[1])]
    groups, known, none = without_copies(kept)
    left = [known[min(g)] for g in groups.values()] + none
    texts = {(r[0], lower(r[1] or ""), r[3]): r for r in left}
    assert len(texts) == len(left)
    cut = [(i, t) for i, _, _, t in removed(left)]
    got = sort(pipeline.run(spark, path).collect())
    want = {c: n for c in coded(set(cut)) for n in [cut.count((c[0], c))]}
    assert got and set(got) <= set(want)
    taken = spark.createDataFrame([(r[0], t, r[3]) for r, (i, t) in zip(sorted(left, key=lambda r: str(r[0])), sorted(cut, key=lambda c: str(c[0])), strict=True)], "doc_id long, text string, source string")
    mixed = [(r["doc_id"], r["text"]) for r in pipeline.source_mixing(spark, taken, path).collect()]
    assert got == sort(coded(mixed))


def test_nothing(spark, docs):
    none = docs.where("false")
    for name, stage in pipeline.STAGES:
        assert stage(spark, none, "").count() == 0, name
