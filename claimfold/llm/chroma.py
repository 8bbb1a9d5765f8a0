"""Audio fingerprints from pitch classes, and search by aligned bit errors.

A recording (16-bit mono PCM) becomes frames of energy in the twelve pitch
classes.  Sums over rectangles of that picture come from its integral image;
FILTERS differences of such sums, two bits each in Gray code, pack into one
32-bit integer a frame.  The thresholds cut each filter's values into four levels
of like size on a bounded sample, so that bits of unlike recordings are unlike.

Recordings of equal fingerprints form a class; only classes are searched, and
members take their class's result, so many copies cost one search.  A query
probes the index with its integers and with those that its weak bits, the ones
nearest to a threshold, may have been; the histogram of position differences
names the offsets, and the wrong bits there decide.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import settle, thin
from .words import Words, chunks, mix64

RATE, FRAME, HOP = 4000, 768, 256
SPAN = 16
SALTS, HOT = 16, 20_000
#: Recordings that thresholds are learnt from, at most; weak bits of an integer that a query turns over.
SAMPLE, WEAK = 500, 6
#: Places that recordings must share, if the shorter one has as many; below FEW places fewer errors are allowed.
OVERLAP, FEW = 24, 8


def _filters() -> list[tuple[int, int, int, int]]:
    """(shape, lowest class, classes, frames) by rule: every shape at several places and sizes."""
    draw = mix64(np.arange(1, 65, dtype=np.uint64)).astype(np.int64) & 0xFFFF
    out = []
    for k in range(16):
        height = 2 + int(draw[k] % 5) * 2
        out.append((k % 6, int(draw[16 + k] % (13 - height)), height, 2 + int(draw[32 + k] % 8) * 2))
    return out


FILTERS = _filters()


def _bins() -> np.ndarray:
    """Weights from spectrum bins to pitch classes, 55 Hz to the top."""
    hz = np.arange(FRAME // 2 + 1) * RATE / FRAME
    weight = np.zeros((len(hz), 12), dtype=np.float32)
    for i in np.flatnonzero(hz >= 55):
        weight[i, round(12 * math.log2(hz[i] / 440)) % 12] = 1
    return weight


_BINS, _TAPER = _bins(), np.hanning(FRAME).astype(np.float32)


#: Frames transformed at once (what fits a processor's cache); steps of a frame's energy and of its powers, so that
#: sums are of whole numbers and exact in any order (single precision holds 2 ** 24).
FRAMES, STEPS, POWERS = 256, 1 << 16, 1 << 18


def _laid(arrays: list[np.ndarray], least: int, kind: type) -> tuple[np.ndarray, np.ndarray]:
    """Arrays one after another, those that aren't empty filled up with zeros to `least` rows; and where each starts."""
    sizes = np.array([max(len(a), least) if len(a) else 0 for a in arrays], dtype=np.int64)
    ends = np.cumsum(sizes)
    out = np.zeros((int(ends[-1]) if len(ends) else 0, *(arrays[0].shape[1:] if arrays else ())), dtype=kind)
    for a, start in zip(arrays, (ends - sizes).tolist(), strict=True):
        out[start : start + len(a)] = a
    return out, ends - sizes


def chroma(recordings: list[np.ndarray]) -> list[np.ndarray]:
    """Frames of pitch-class energy of each recording, of length STEPS each, in whole numbers; none for a recording of no length.

    All recordings go through the transform together, but a frame's numbers do not
    depend on the others: powers are rounded before they are summed.
    """
    sizes = np.array([(max(len(p), FRAME) - FRAME) // HOP + 1 if len(p) else 0 for p in recordings], dtype=np.int64)
    whole, begin = _laid([np.asarray(p) for p in recordings], FRAME, np.int16)
    if not len(whole):
        return [np.zeros((0, 12), np.int64)] * len(recordings)
    start = np.repeat(begin, sizes) + HOP * (np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes))
    frames = np.lib.stride_tricks.sliding_window_view(whole, FRAME)
    out = np.empty((len(start), 12), dtype=np.int64)
    for lo in range(0, len(start), FRAMES):
        got = np.fft.rfft(frames[start[lo : lo + FRAMES]] * _TAPER, axis=1)
        power = got.real**2
        power += got.imag**2
        power *= (np.float32(POWERS) / np.maximum(power.max(axis=1), np.float32(1e-9)))[:, None]
        classes = (np.rint(power, out=power) @ _BINS).astype(np.float64)
        norm = np.sqrt(sum(classes[:, k] ** 2 for k in range(12)))
        out[lo : lo + FRAMES] = np.rint(classes / np.maximum(norm, 1e-9)[:, None] * STEPS)
    return np.split(out, np.cumsum(sizes)[:-1])


def filter_values(pictures: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(FILTERS x places) log ratios of all pictures in a row, from one integral image; and each picture's places."""
    sizes = np.array([max(len(p), SPAN) if len(p) else 0 for p in pictures], dtype=np.int64)
    if not sizes.sum():
        return np.zeros((len(FILTERS), 0)), np.zeros(len(pictures), np.int64)
    whole, _ = _laid([*pictures, np.zeros((SPAN, 12), np.int64)], SPAN, np.int64)
    area = np.zeros((13, len(whole) + 1), dtype=np.int64)
    np.cumsum(whole.cumsum(axis=0).T, axis=0, out=area[1:, 1:])
    n = len(whole) - SPAN

    def box(t0: int, t1: int, y0: int, y1: int) -> np.ndarray:
        sums = area[y1] - area[y0]
        return sums[t1 : t1 + n] - sums[t0 : t0 + n]

    out = np.empty((len(FILTERS), n))
    for k, (shape, y, h, t) in enumerate(FILTERS):
        third, quarter = max(1, h // 3), max(1, t // 3)
        full = box(0, t, y, y + h)
        if shape == 0:
            a = full
        elif shape == 1:
            a = box(0, t, y + h // 2, y + h)
        elif shape == 2:
            a = box(0, t // 2, y, y + h)
        elif shape == 3:
            a = box(0, t // 2, y + h // 2, y + h) + box(t // 2, t, y, y + h // 2)
        elif shape == 4:
            a = box(0, t, y + third, y + h - third)
        else:
            a = box(quarter, t - quarter, y, y + h)
        np.log((STEPS + a) / (STEPS + (full - a if shape else 0)), out=out[k])
    inside = np.concatenate([np.arange(e - s, e - SPAN + 1) for s, e in zip(sizes, np.cumsum(sizes), strict=True) if s])
    return out[:, inside], np.maximum(sizes - SPAN + 1, 0) * (sizes > 0)


def _levels(values: np.ndarray) -> np.ndarray:
    """(FILTERS x 3) thresholds that cut each filter's values into four levels of like size; even ones where there is no sound."""
    if not values.shape[1]:
        return np.tile([-0.1, 0.0, 0.1], (len(FILTERS), 1))
    return np.quantile(values, [0.25, 0.5, 0.75], axis=1).T


def fingerprints(pictures: list[np.ndarray], levels: np.ndarray, weak: int = 0) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Packed integers of each picture, one for every place of a window of SPAN frames, one at least; and masks of weak bits.

    A place's row of masks has `weak` single bits: those whose threshold its values are closest to.
    """
    values, sizes = filter_values(pictures)
    out = np.zeros(values.shape[1], dtype=np.uint32)
    far = np.empty((values.shape[1], len(FILTERS) if weak else 0))
    bit = np.empty(far.shape, dtype=np.uint32)
    for k, v in enumerate(values):
        level = np.searchsorted(levels[k], v).astype(np.uint32)
        out = out << np.uint32(2) | (level ^ level >> np.uint32(1))
        if weak:
            # Crossing the middle threshold turns the higher bit of a level, crossing another the lower one.
            gap = np.abs(v[:, None] - levels[k])
            near = gap.argmin(axis=1)
            far[:, k] = gap[np.arange(len(v)), near] / max(levels[k][2] - levels[k][0], 1e-9)
            bit[:, k] = np.where(near == 1, np.uint32(2), np.uint32(1)) << np.uint32(2 * (len(FILTERS) - 1 - k))
    masks = np.take_along_axis(bit, np.argsort(far, axis=1, kind="stable")[:, :weak], axis=1) if weak else np.zeros((len(out), 0), np.uint32)
    cut = np.cumsum(sizes)[:-1]
    return np.split(out, cut), np.split(masks, cut)


def render(column: pa.Array, samples: int = 128, notes: int = 36) -> list[np.ndarray]:
    """A synthetic recording of each text: a short tone for each word, its pitch by the word's hash."""
    tone = np.sin(2 * np.pi * np.outer(110 * 2 ** (np.arange(notes) / 12), np.arange(samples) / RATE)) * 12000
    tone = tone.astype(np.int16)
    w = Words(column, lower=True)
    pitch = (w.hashes() % np.uint64(notes)).astype(np.int64)
    return [tone[pitch[a:b]].reshape(-1) for a, b in zip(w.first[:-1], w.first[1:], strict=True)]


def _pcm(media: pa.Array, rendered: bool) -> list[np.ndarray]:
    return render(media) if rendered else [np.frombuffer((p or b"")[: len(p or b"") // 2 * 2], "<i2") for p in media.to_pylist()]


def fit(df: DataFrame, id: Column, media: Column, rendered: bool = False, sample: int = SAMPLE, places: int = 256) -> np.ndarray:
    """Thresholds from at most `sample` recordings, those of the smallest hashes, and `places` places spread over each."""
    hashed = df.select(media.alias("media"), F.xxhash64(id, media).alias("h")).where("media is not null")
    few = thin(hashed, "h", hashed.count(), sample).orderBy("h").limit(sample).select("media")

    def run(batches):
        values = [np.zeros((len(FILTERS), 0))]
        for b in batches:
            for x, y in chunks(b.column(0), 1 << 18 if rendered else 1 << 23):
                got, sizes = filter_values(chroma(_pcm(b.column(0).slice(x, y - x), rendered)))
                ends = np.cumsum(sizes)
                values += [got[:, np.unique(np.linspace(e - n, e - 1, min(n, places)).astype(np.int64))] for n, e in zip(sizes.tolist(), ends.tolist(), strict=True) if n]
        yield pa.RecordBatch.from_arrays([pa.array([_levels(np.concatenate(values, axis=1)).ravel()], pa.list_(pa.float64()))], names=["levels"])

    got = few.coalesce(1).mapInArrow(run, "levels array<double>").collect()  # one row, none for an empty table
    return np.array(got[0][0]).reshape(-1, 3) if got else _levels(np.zeros((len(FILTERS), 0)))


def fingerprint_column(df: DataFrame, id: Column, media: Column, query: Column, levels: np.ndarray, rendered: bool = False) -> DataFrame:
    """(id, query, n, d1, d2, prints, masks) from a PCM column, or from a text column to be rendered.

    masks has WEAK single bits for each integer of a query's recording, and is empty for others.
    """
    kind = df.select(id.alias("id")).schema["id"].dataType.simpleString()

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            for x, y in chunks(b.column("media"), 1 << 18 if rendered else 1 << 23):
                asked = np.asarray(b.column("query").slice(x, y - x).to_numpy(zero_copy_only=False), dtype=bool)
                pictures = chroma(_pcm(b.column("media").slice(x, y - x), rendered))
                prints, _ = fingerprints(pictures, levels)
                _, weak = fingerprints([p for p, q in zip(pictures, asked, strict=True) if q], levels, WEAK)
                weak = iter(weak)
                masks = [next(weak).ravel() if q else np.zeros(0, np.uint32) for q in asked]
                flat, ends = _flat(prints)
                weight = np.arange(len(flat), dtype=np.uint64) - np.repeat(ends[:-1], np.diff(ends)).astype(np.uint64)
                digest = []
                for seed in (1, 2):
                    v = mix64(flat.astype(np.uint64) + (weight << np.uint64(32)) + np.uint64(seed << 60))
                    sums = np.concatenate([[np.uint64(0)], np.cumsum(v, dtype=np.uint64)])
                    digest.append((sums[ends[1:]] - sums[ends[:-1]]).view(np.int64))
                lists = [pa.ListArray.from_arrays(pa.array(e.astype(np.int32)), pa.array(f.view(np.int32))) for f, e in ((flat, ends), _flat(masks))]
                yield pa.RecordBatch.from_arrays([b.column("id").slice(x, y - x), pa.array(asked), pa.array(np.diff(ends)), *map(pa.array, digest), *lists], names=["id", "query", "n", "d1", "d2", "prints", "masks"])

    rows = df.select(id.alias("id"), F.coalesce(query, F.lit(False)).alias("query"), media.alias("media"))
    return rows.mapInArrow(run, f"id {kind}, query boolean, n long, d1 long, d2 long, prints array<int>, masks array<int>")


def _flat(arrays: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.concatenate([np.zeros(0, np.uint32), *arrays]), np.cumsum([0, *map(len, arrays)])


def allowed_errors(shared: Column, most_errors: float) -> Column:
    """The share of wrong bits up to which recordings that share so many places match: less for few places, where chance does more."""
    return F.lit(most_errors) * F.least(F.lit(1.0), shared / FEW)


def search(df: DataFrame, id: Column, media: Column, query: Column, rendered: bool = False, levels: np.ndarray | None = None, most_errors: float = 0.2) -> DataFrame:
    """(id, n_prints, class_id, n_matches, best_id, best_offset, best_errors), a row for every recording.

    Recordings where `query` holds are searched in all.  class_id is the smallest
    id of equal fingerprints.  n_matches counts the query classes, other than the
    recording's own, that match it: at some offset they share all places of the
    shorter one, or OVERLAP, and at most `most_errors` of the bits there differ
    (`allowed_errors` for fewer than FEW places).  best_* tell the match of the
    fewest errors; of equal ones that of the smallest id, then offset.

    An offset is looked at if an integer of the query, or one that up to two of
    its WEAK weak bits turn it into, stands there in the recording; neighbours that are
    equal count once, so silence costs little.  Rows without an id or without
    sound match nothing; repeated rows come back as often, each alike; an empty
    table gives no rows.  An id may be a structure of several columns.
    """
    levels = fit(df, id, media, rendered) if levels is None else levels
    all_ = settle(fingerprint_column(df, id, media, query, levels, rendered), "chroma-prints")
    members = all_.where("n > 0 and id is not null").groupBy("n", "d1", "d2")
    classes = settle(members.agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.max("query").alias("query"), F.first("prints").alias("prints"), F.max("masks").alias("masks")), "chroma-classes")
    # First places of runs of equal integers.
    starts = F.filter(F.transform("prints", lambda v, i: F.struct(v.alias("value"), i.alias("at"))), lambda x: (x["at"] == 0) | (x["value"] != F.get("prints", x["at"] - 1)))
    weak = F.slice("masks", F.col("at") * WEAK + 1, F.lit(WEAK))
    pairs = F.flatten(F.transform(weak, lambda m, i: F.transform(F.slice(weak, i + 2, F.lit(WEAK)), lambda o: m.bitwiseXOR(o))))
    turned = F.concat(F.array(F.lit(0)), weak, pairs)
    asked = classes.where("query").select(F.col("d1").alias("q"), "masks", F.explode(starts).alias("s")).select("q", "masks", "s.*")
    asked = asked.select("q", F.col("at").alias("qp"), F.explode(F.transform(turned, lambda m: F.col("value").bitwiseXOR(m))).alias("value"))
    held = classes.select(F.col("d1").alias("r"), F.explode(starts).alias("s")).select("r", F.col("s.at").alias("rp"), F.col("s.value").alias("value"))
    # Of the places of all recordings only those whose integer is asked for go on: one exchange of the index.
    held = settle(held.join(asked.select("value").distinct(), "value", "left_semi"), "chroma-held")
    votes = salted_join(asked, held).where("q <> r").groupBy("q", "r", (F.col("rp") - F.col("qp")).alias("offset")).count()
    offsets = votes.groupBy("q", "r").agg(F.max("count").alias("most"), F.collect_list(F.struct("count", "offset")).alias("o"))
    offsets = offsets.select("q", "r", F.transform(F.filter("o", lambda x: x["count"] * 2 >= F.col("most")), lambda x: x["offset"]).alias("offsets"))
    side = lambda c, p: classes.select(F.col("d1").alias(c), F.col("rep").alias(f"{c}_rep"), F.struct("n", "d1", "d2").alias(f"{c}_key"), F.col("prints").alias(p))
    both = offsets.join(side("q", "qs"), "q").join(side("r", "rs"), "r")

    def judge(offset: Column) -> Column:
        first_q, first_r = F.greatest(-offset, F.lit(0)), F.greatest(offset, F.lit(0))
        shared = F.least(F.size("qs") - first_q, F.size("rs") - first_r)
        wrong = F.aggregate(F.zip_with(F.slice("qs", first_q + 1, shared), F.slice("rs", first_r + 1, shared), lambda a, b: F.bit_count(a.bitwiseXOR(b).cast("long").bitwiseAND(F.lit(0xFFFFFFFF)))), F.lit(0), lambda s, x: s + x)
        fits = (shared >= F.least(F.size("qs"), F.size("rs"), F.lit(OVERLAP))) & (wrong / (32.0 * shared) <= allowed_errors(shared, most_errors))
        return F.when(fits, F.struct((wrong / (32.0 * shared)).alias("errors"), offset.alias("offset")))

    scored = both.select("q_rep", "r_key", F.array_min(F.filter(F.transform("offsets", judge), lambda x: x.isNotNull())).alias("b")).where("b is not null")
    per = scored.groupBy("r_key").agg(F.count(F.lit(1)).alias("n_matches"), F.min(F.struct(F.col("b.errors").alias("errors"), F.col("q_rep").alias("q"), F.col("b.offset").alias("offset"))).alias("best"))
    rows = all_.select("id", "n", "d1", "d2", F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int").alias("salt"))
    results = classes.join(per, F.struct("n", "d1", "d2") == F.col("r_key"), "left").where("copies > 1 or n_matches is not null").select("n", "d1", "d2", "rep", "n_matches", "best", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    out = rows.join(results, ["n", "d1", "d2", "salt"], "left")
    known = (F.col("n") > 0) & F.col("id").isNotNull()
    took = lambda c: F.when(known, F.col(c))
    return out.select("id", F.col("n").alias("n_prints"), F.when(known, F.coalesce("rep", "id")).otherwise(F.col("id")).alias("class_id"), F.coalesce(took("n_matches"), F.lit(0)).cast("long").alias("n_matches"), took("best.q").alias("best_id"), took("best.offset").alias("best_offset"), took("best.errors").alias("best_errors"))


def salted_join(asked: DataFrame, held: DataFrame) -> DataFrame:
    """Join on value; a value that more than HOT places hold is split over SALTS tasks, and its questions repeated."""
    hot = settle(held.groupBy("value").count().where(F.col("count") > HOT).select("value"), "chroma-hot")
    if hot.isEmpty():
        return asked.join(held, "value")
    marked = hot.withColumn("hot", F.lit(True))
    places = held.join(marked, "value", "left").withColumn("salt", F.when(F.col("hot"), F.pmod(F.xxhash64("r", "rp"), F.lit(SALTS))).otherwise(0))
    questions = asked.join(marked, "value", "left").withColumn("salt", F.explode(F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))))
    return questions.drop("hot").join(places.drop("hot"), ["value", "salt"])
