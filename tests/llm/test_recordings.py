"""Fingerprints against plain sums, and the search against all pairs and offsets."""


import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from claimfold.llm import chroma


def tune(rng, n):
    return np.concatenate([np.sin(2 * np.pi * 110 * 2 ** (k / 12) * np.arange(300) / chroma.RATE) * 8000 for k in rng.integers(0, 36, n)])


def plain_prints(picture, levels):
    """Integers of one picture from sums over rectangles, one by one."""
    p = picture.astype(object) if len(picture) >= chroma.SPAN else np.vstack([picture, np.zeros((chroma.SPAN - len(picture), 12), np.int64)]).astype(object)
    out = []
    for i in range(len(p) - chroma.SPAN + 1):
        box = lambda t0, t1, y0, y1, i=i: int(p[i + t0 : i + t1, y0:y1].sum())
        code = 0
        for (shape, y, h, t), cut in zip(chroma.FILTERS, levels, strict=True):
            full = box(0, t, y, y + h)
            third, quarter = max(1, h // 3), max(1, t // 3)
            a = [
                full, box(0, t, y + h // 2, y + h), box(0, t // 2, y, y + h), box(0, t // 2, y + h // 2, y + h) + box(t // 2, t, y, y + h // 2),
                box(0, t, y + third, y + h - third), box(quarter, t - quarter, y, y + h),
            ][shape]
            value = np.log((chroma.STEPS + a) / (chroma.STEPS + (full - a if shape else 0)))
            level = int(sum(c < value for c in cut))
            code = code << 2 | (level ^ level >> 1)
        out.append(code)
    return out


def test_prints_by_plain_sums():
    rng = np.random.default_rng(1)
    pictures = [rng.integers(0, chroma.STEPS, (n, 12)) for n in (5, 20, 31)] + [np.zeros((0, 12), np.int64)]
    levels = chroma._levels(chroma.filter_values(pictures)[0])
    together, masks = chroma.fingerprints(pictures, levels, 6)
    assert [len(p) for p in together] == [1, 5, 16, 0]
    for p, t, m in zip(pictures[:3], together, masks, strict=False):
        assert t.tolist() == plain_prints(p, levels)
        assert all(bin(int(b)).count("1") == 1 for b in m.ravel()) and all(len(set(r)) == 6 for r in m.tolist())


def test_a_recording_has_the_same_prints_in_any_company():
    rng = np.random.default_rng(2)
    pcm = [tune(rng, n).astype(np.int16) for n in (1, 3, 40, 90)] + [np.zeros(0, np.int16), np.zeros(5000, np.int16)]
    together = chroma.chroma(pcm)
    for a, b in zip(pcm, together, strict=True):
        assert (chroma.chroma([a])[0] == b).all()


def matches(prints, most=0.2):
    """{(i, j): (errors, offset)} of all pairs that match, over all offsets."""
    ones = np.array([bin(i).count("1") for i in range(1 << 16)])
    out = {}
    for i, a in enumerate(prints):
        for j, b in enumerate(prints):
            best = None
            for offset in range(-len(a) + 1, len(b)):
                x, y = max(0, -offset), max(0, offset)
                n = min(len(a) - x, len(b) - y)
                if i == j or n < min(len(a), len(b), chroma.OVERLAP) or n < 1:
                    continue
                d = a[x : x + n] ^ b[y : y + n]
                errors = (ones[d & 0xFFFF].sum() + ones[d >> 16].sum()) / (32 * n)
                if errors <= most * min(1, n / chroma.FEW) and (best is None or (errors, offset) < best):
                    best = (errors, offset)
            if best:
                out[i, j] = best
    return out


def test_search_by_all_pairs(spark):
    """All lengths, shifts and noise; every answer is right, and at least 0.9 of the matches are found."""
    rng = np.random.default_rng(0)
    pcm = []
    for i in range(30):
        x = tune(rng, int(rng.integers(2, 160)))
        cut = int(rng.integers(0, max(1, len(x) // 3))) // chroma.HOP * chroma.HOP
        y = x[cut : len(x) - int(rng.integers(0, max(1, len(x) // 4)))] * 0.5
        pcm += [x, y + rng.normal(0, 30 * 3 ** (i % 5), len(y)), x + rng.normal(0, 200, len(x))]
    pcm = [x.astype("<i2") for x in pcm]
    rows = [(i, bytearray(x.tobytes())) for i, x in enumerate(pcm)] + [(200, bytearray(pcm[0].tobytes())), (200, bytearray(pcm[0].tobytes())), (201, None), (202, bytearray()), (None, bytearray(pcm[2].tobytes()))]
    df = spark.createDataFrame(rows, "id long, pcm binary").withColumn("n", F.lit("clash")).withColumn("query", F.lit(1))
    levels = chroma.fit(df, F.col("id"), F.col("pcm"))
    got = chroma.search(df, F.col("id"), F.col("pcm"), F.col("id") % 3 == 0, levels=levels).collect()
    assert len(got) == len(rows)
    prints, _ = chroma.fingerprints(chroma.chroma(pcm), levels)
    truth = {k: v for k, v in matches(prints).items() if k[0] % 3 == 0}
    by = {r["id"]: r for r in got}
    found = wanted = 0
    for j in range(len(pcm)):
        own = {i: v for (i, k), v in truth.items() if k == j and by[i]["class_id"] != by[j]["class_id"]}
        wanted += len(own)
        found += by[j]["n_matches"]
        assert by[j]["n_matches"] <= len(own)
        if by[j]["n_matches"]:
            errors, _ = own[by[j]["best_id"]]
            a, b, offset = prints[by[j]["best_id"]], prints[j], by[j]["best_offset"]
            x, y = max(0, -offset), max(0, offset)
            n = min(len(a) - x, len(b) - y)
            wrong = sum(bin(int(v)).count("1") for v in a[x : x + n] ^ b[y : y + n])
            assert by[j]["best_errors"] == wrong / (32 * n) >= errors - 1e-12
    assert wanted > 40 and found >= 0.9 * wanted, (found, wanted)
    copies = [r for r in got if r["id"] == 200]
    assert len(copies) == 2 and copies[0] == copies[1] and copies[0]["class_id"] == by[0]["class_id"]
    assert by[201]["n_prints"] == by[202]["n_prints"] == 0 and by[None]["n_matches"] == 0 and by[None]["class_id"] is None
    assert chroma.search(df.where("false"), F.col("id"), F.col("pcm"), F.col("id") % 3 == 0).count() == 0


def test_hot_values_are_split(spark, monkeypatch):
    monkeypatch.setattr(chroma, "HOT", 3)
    asked = spark.createDataFrame([(1, 0, 7), (1, 1, 8), (2, 0, 9)], "q long, qp int, value int")
    held = spark.createDataFrame([(k, k % 5, 7) for k in range(40)] + [(50, 0, 8)], "r long, rp int, value int")
    got = sorted((r["q"], r["qp"], r["r"], r["rp"]) for r in chroma.salted_join(asked, held).collect())
    assert got == sorted([(1, 0, k, k % 5) for k in range(40)] + [(1, 1, 50, 0)])


def test_ids_of_several_columns(spark):
    rows = [(None, 0, "one two three"), (None, 1, "one two three"), (5, 0, "one two three"), (100, 3, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn int, text string")
    got = chroma.search(df, F.struct("conv_id", "turn"), F.col("text"), F.col("conv_id") % 100 == 0, rendered=True).select("id.*", "class_id").collect()
    assert {(r["conv_id"], r["turn"]) for r in got} == {(None, 0), (None, 1), (5, 0), (100, 3)}


def test_render_repeats():
    a, b = chroma.render(pa.array(["one two", "ONE two"]))
    assert (a == b).all() and len(chroma.render(pa.array([None]))[0]) == 0
