"""The five stages, each against what its operator's definition says of its own input."""

import corpus_pipeline as pipeline
import pytest

from claimfold.llm import queries

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    from claimfold.llm.shared import settle

    docs = queries.documents(spark, SF)
    out = [("documents", docs)]
    for name, f in pipeline.STAGES:
        docs = settle(f(spark, docs, SF), f"test-{name}")
        out.append((name, docs))
    return dict(out)


def test_columns_and_order(stages):
    names = list(stages)
    assert names[1:] == ["quality_rules", "near_duplicates", "substring_dedup", "source_mixing", "bpe_tokens"]
    for n in names[1:-1]:
        assert stages[n].columns == stages["documents"].columns
    assert stages["bpe_tokens"].columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_decisions_take_effect(stages):
    ids = {n: [r["doc_id"] for r in d.select("doc_id").collect()] for n, d in stages.items()}
    assert set(ids["quality_rules"]) < set(ids["documents"])
    assert set(ids["near_duplicates"]) <= set(ids["quality_rules"])
    assert sorted(ids["substring_dedup"]) == sorted(ids["near_duplicates"])
    assert set(ids["source_mixing"]) <= set(ids["substring_dedup"])
    assert sorted(ids["bpe_tokens"]) == sorted(ids["source_mixing"])


def test_run_repeats(spark):
    rows = lambda: sorted(map(tuple, pipeline.run(spark, SF).collect()))
    first = rows()
    assert first and first == rows()


def test_pairs_at_the_threshold_go(spark):
    """A copy with one word changed and eight more at its end is of similarity 0.80 to 0.85."""
    words = [f"w{i}" for i in range(96)]
    near = [*words[:46], "other", *words[47:], *(f"x{i}" for i in range(8))]
    a, b = ({tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (words, near))
    assert 0.80 <= len(a & b) / len(a | b) < 0.85
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(near)), (3, "alone here")], "doc_id long, text string")
    assert {r["doc_id"] for r in pipeline.near_duplicates(spark, docs, SF).collect()} == {1, 3}


def test_bands_follow_the_threshold():
    from claimfold.llm import minhash

    assert minhash.band_rows(85) == 6 and minhash.band_rows(80) == 5
    for percent in range(10, 100):
        rows = minhash.band_rows(percent)
        assert (1 - (percent / 100) ** rows) ** (2 * minhash.PERMUTATIONS // rows) < 1e-6
    with pytest.raises(ValueError):
        minhash.band_rows(5)
