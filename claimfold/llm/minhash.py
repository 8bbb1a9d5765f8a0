"""Near-duplicate groups by min-max hashing, with every link confirmed on full sets.

A document's set holds the hashes of its distinct five-word shingles.  Under each
of `PERMUTATIONS` hash functions both the smallest and the largest value are
kept: one evaluation gives two signature values.  Bands of some minima or of as
many maxima bring candidates together; `band_rows` takes as many as let a pair at
the threshold miss all bands with a probability below `MISSED`: 30 bands of 6 at
0.85, 36 of 5 at 0.80.

Stages, all of which move rows in proportion to the documents:

1. `sketch`: one narrow pass to set size, 128-bit set digest and band keys.
2. Documents of equal sets collapse to one node, a hash of the set, by a combining aggregate.
3. Band keys that two or more sets share give star edges, salted by document,
   and their connected components are the candidate groups.
4. Texts of candidates only are dealt to their group; groups beyond a block's
   size are split into blocks, and each pair of blocks is one bounded task.  A
   task intersects full sets through products of 0/1 matrices and emits a
   spanning forest of the links it confirms, never the pairs.
5. Components of the confirmed links, then membership of the equal sets.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import Forest, components, fresh, settle, spread
from .words import Words, chunks, mix64, rolling, window_owner

PERMUTATIONS, WIDTH = 90, 5
MISSED = 1e-6
SALTS = 32
#: Documents of a block: a sixteenth of the group, within these bounds.
BLOCK_LEAST, BLOCK_MOST = 256, 4096
#: Shingles of a block: a task holds two blocks, whatever the length of their texts, unless one text alone is longer.
BLOCK_SHINGLES = 1_500_000

_MULTIPLY = mix64(np.arange(1, PERMUTATIONS + 1, dtype=np.uint64)) | np.uint64(1)
_ADD = mix64(np.arange(1001, PERMUTATIONS + 1001, dtype=np.uint64))


def band_rows(percent: int) -> int:
    """Rows of a band: the most, of those that divide the minima evenly, that keep the miss below MISSED."""
    for rows in range(PERMUTATIONS, 0, -1):
        if PERMUTATIONS % rows == 0 and (1 - (percent / 100) ** rows) ** (2 * PERMUTATIONS // rows) < MISSED:
            return rows
    raise ValueError(f"no bands of {2 * PERMUTATIONS} values find pairs at {percent} percent")


def shingle_sets(column: pa.Array, width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of all texts in a row, and where each text's set starts.

    A text of fewer words than `width` has its whole word sequence as its one
    shingle; a text without words, or a null, has the empty set.
    """
    w = Words(column, lower=True)
    h = w.hashes()
    first, owner = window_owner(w, width)
    keys = rolling(h, width)[first]
    short = np.flatnonzero((w.count > 0) & (w.count < width))
    if len(short):
        own = [rolling(h[w.first[i] : w.first[i] + w.count[i]], w.count[i], seed=width + 2)[:1] for i in short]
        keys, owner = np.concatenate([keys, *own]), np.concatenate([owner, short])
    order = np.lexsort((keys, owner))
    keys, owner = keys[order], owner[order]
    new = np.ones(len(keys), dtype=bool)
    new[1:] = (keys[1:] != keys[:-1]) | (owner[1:] != owner[:-1])
    keys, owner = keys[new], owner[new]
    return keys, np.searchsorted(owner, np.arange(w.n_docs + 1))


def sketch_column(column: pa.Array, rows: int) -> dict[str, np.ndarray]:
    """n, the digest (a, b) and the keys of all bands of `rows` values of each text's set (keys mean nothing where n is 0)."""
    parts, n_bands = [], 2 * PERMUTATIONS // rows
    for x, y in chunks(column):
        keys, start = shingle_sets(column.slice(x, y - x))
        n = np.diff(start)
        full = np.flatnonzero(n)
        at = start[:-1][full]
        sig = np.zeros((len(n), 2 * PERMUTATIONS), dtype=np.uint64)
        digest = np.zeros((len(n), 2), dtype=np.uint64)
        if len(full):
            for k in range(PERMUTATIONS):
                v = keys * _MULTIPLY[k] + _ADD[k]
                sig[full, k] = np.minimum.reduceat(v, at)
                sig[full, PERMUTATIONS + k] = np.maximum.reduceat(v, at)
            digest[full, 0] = np.add.reduceat(keys, at)
            digest[full, 1] = np.add.reduceat(mix64(keys + np.uint64(0x1F83D9ABFB41BD6B)), at)
        bands = np.zeros((len(n), n_bands), dtype=np.uint64)
        for j in range(rows):
            bands = mix64(bands * np.uint64(0x9E3779B97F4A7C15) + sig[:, j::rows])
        bands += np.arange(1, n_bands + 1, dtype=np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
        parts.append((n, digest.view(np.int64), mix64(bands).view(np.int64)))
    if not parts:
        return {"n": np.zeros(0, np.int64), "digest": np.zeros((0, 2), np.int64), "bands": np.zeros((0, n_bands), np.int64)}
    return {k: np.concatenate([p[i] for p in parts]) for i, k in enumerate(("n", "digest", "bands"))}


def sketch(docs: DataFrame, id: str, text: str, rows: int) -> DataFrame:
    """(id, print, n, a, b, bands, node): print is a hash of the text, node one of the set."""

    def run(batches):
        for b in batches:
            got = sketch_column(b.column(2), rows)
            bands = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * (2 * PERMUTATIONS // rows)), pa.array(got["bands"].reshape(-1)))
            arrays = [b.column(0), b.column(1), pa.array(got["n"]), pa.array(got["digest"][:, 0]), pa.array(got["digest"][:, 1]), bands]
            yield pa.RecordBatch.from_arrays(arrays, names=["id", "print", "n", "a", "b", "bands"])

    drawn = _texts(docs, id, text).mapInArrow(run, "id long, print long, n long, a long, b long, bands array<long>")
    return drawn.withColumn("node", F.xxhash64("n", "a", "b"))


def _texts(docs: DataFrame, id: str, text: str) -> DataFrame:
    return docs.select(F.col(f"`{id}`").cast("long").alias("id"), F.xxhash64(F.col(f"`{text}`")).alias("print"), F.col(f"`{text}`").alias("text"))


def _linked(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i of left, j of right) whose sets have 100 * both >= percent * either, by exact counts."""
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    flat, row = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    order = np.argsort(flat, kind="stable")
    flat, row = flat[order], row[order]
    new = np.ones(len(flat), dtype=bool)
    new[1:] = flat[1:] != flat[:-1]
    column = np.cumsum(new) - 1
    shared = np.bincount(column) > 1  # what one set alone holds is in no intersection
    keep = shared[column]
    row, column = row[keep], (np.cumsum(shared) - 1)[column[keep]]
    n, both = int(shared.sum()), np.zeros((len(left), len(right)), dtype=np.float32)
    step = max(64, min(n, (4 << 20) // max(1, len(sets))))
    for lo in range(0, n, step):
        a, z = np.searchsorted(column, [lo, lo + step])
        m = np.zeros((len(sets), min(step, n - lo)), dtype=np.float32)
        m[row[a:z], column[a:z] - lo] = 1
        both += m[left] @ m[right].T
    both = both.astype(np.int64)
    i, j = np.nonzero(100 * both >= percent * (sizes[left][:, None] + sizes[right][None] - both))
    return left[i], right[j]


def _confirm(percent: int):
    """Tasks arrive whole and in order; each gives a spanning forest of its confirmed links."""

    def solve(rows):
        ids = np.concatenate([r.column("node").to_numpy(zero_copy_only=False) for r in rows])
        part = np.concatenate([r.column("part").to_numpy(zero_copy_only=False) for r in rows])
        text = pa.chunked_array([r.column("text") for r in rows]).combine_chunks()
        text = text.chunk(0) if isinstance(text, pa.ChunkedArray) else text
        sets: list[np.ndarray] = []
        for x, y in chunks(text):
            keys, start = shingle_sets(text.slice(x, y - x))
            sets += [keys[s:e] for s, e in zip(start[:-1], start[1:], strict=True)]
        left = np.flatnonzero(part != 2)
        right = np.flatnonzero(part != 1)
        forest, u, v = Forest(len(ids)), [], []
        order = np.argsort(ids)
        rank = np.empty(len(ids), dtype=np.int64)
        rank[order] = np.arange(len(ids))
        for lo in range(0, len(left), 1024):
            for i, j in zip(*_linked(sets, left[lo : lo + 1024], right, percent), strict=True):
                if i != j and forest.join(rank[i], rank[j]):
                    u.append(ids[i])
                    v.append(ids[j])
        return u, v

    def run(batches):
        held, key, out_u, out_v, seen = [], None, [], [], set()
        for b in batches:
            if not b.num_rows:
                continue
            keys = b.column("task").to_pylist()
            edges = [0, *(i for i in range(1, len(keys)) if keys[i] != keys[i - 1]), len(keys)]
            for s, e in zip(edges[:-1], edges[1:], strict=True):
                if keys[s] != key and held:
                    u, v = solve(held)
                    out_u += u
                    out_v += v
                if keys[s] != key:
                    held, seen = [], set()
                key = keys[s]
                part = b.slice(s, e - s)
                nodes = part.column("node").to_pylist()
                new = [i for i, x in enumerate(nodes) if x not in seen and not seen.add(x)]  # a repeated row counts once
                held.append(part if len(new) == len(nodes) else part.take(pa.array(new, pa.int64())))
        if held:
            u, v = solve(held)
            out_u += u
            out_v += v
        yield pa.RecordBatch.from_arrays([pa.array(out_u, pa.int64()), pa.array(out_v, pa.int64())], names=["u", "v"])

    return run


def near_duplicates(docs: DataFrame, id: str = "doc_id", text: str = "text", percent: int = 85) -> DataFrame:
    """(id, n_shingles, component_id, kept) for every row of docs.

    Links hold where 100 * intersection >= percent * union of the shingle sets.
    component_id is the smallest id reachable.  Rows whose set is empty, and rows
    without an id, are linked with nothing; a null id has a null component and is
    kept.  A row is judged by its own text: rows that repeat an id with one text
    come back as often, each with the same component, and rows that share an id
    with other texts have each their own.  Of ties the smallest id names the
    component.  An empty table gives an empty result; other columns are not read.
    """
    found = labelled(docs, id, text, percent)
    return found.select(F.col("id").alias(id), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), F.coalesce(F.col("id") == F.col("component"), F.lit(True)).alias("kept"))


def labelled(docs: DataFrame, id: str = "doc_id", text: str = "text", percent: int = 85) -> DataFrame:
    """(id, print, n, component, first) for every row; print is a hash of the text.

    first holds for one (id, print) of each component, the smallest; rows without an id are first.
    """
    parts = spread(docs)
    drawn = settle(sketch(docs, id, text, band_rows(percent)), "minhash-sketch")
    sets = drawn.where("n > 0 and id is not null")
    reps = settle(sets.groupBy("n", "a", "b").agg(F.min(F.struct("id", "print")).alias("rep"), F.count_distinct("id", "print").alias("copies"), F.first("bands").alias("bands"), F.first("node").alias("node")), "minhash-sets")

    keyed = reps.select("node", F.explode("bands").alias("key"))
    hubs = keyed.groupBy("key").agg(F.min("node").alias("hub"), F.max("node").alias("last")).where("hub <> last")
    hubs = hubs.select("key", "hub", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    stars = keyed.withColumn("salt", F.pmod(F.xxhash64("node"), F.lit(SALTS)).cast("int")).join(hubs, ["key", "salt"]).where("node <> hub")
    groups = components(stars.select("hub", "node").distinct(), "minhash-candidates")

    # (documents, shingles, blocks) of each group; blocks are by the hash of the node, of bounded rows and shingles.
    groups = groups.join(reps.select("node", "rep", "n"), "node")
    sizes = groups.groupBy("component").agg(F.count(F.lit(1)).alias("size"), F.sum("n").alias("shingles"))
    by_rows = F.col("size") / F.least(F.lit(BLOCK_MOST), F.greatest(F.lit(BLOCK_LEAST), F.ceil(F.col("size") / 16)))
    sizes = sizes.withColumn("blocks", F.ceil(F.greatest(by_rows, F.col("shingles") / BLOCK_SHINGLES)).cast("int"))
    blocked = groups.join(sizes, "component").withColumn("block", F.pmod(F.xxhash64("node", F.lit(7)), "blocks").cast("int"))
    dealt = (
        _texts(docs, id, text)
        .join(blocked.select("node", "rep.id", "rep.print", "component", "block", "blocks").hint("merge"), ["id", "print"])
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        .select(
            "node",
            "text",
            F.xxhash64("component", F.least("block", "other"), F.greatest("block", "other")).alias("task"),
            F.when(F.col("block") == F.col("other"), 0).when(F.col("block") < F.col("other"), 1).otherwise(2).alias("part"),
        )
    )
    links = dealt.repartition(parts, "task").sortWithinPartitions("task").mapInArrow(_confirm(percent), "u long, v long")
    found = components(settle(links, "minhash-links"), "minhash-components").withColumnRenamed("component", "root")
    # The smallest (id, print) of each component, and of each set that several documents have.
    named = reps.select("node", "copies", "rep").join(found, "node", "left")
    least = named.where("root is not null").groupBy("root").agg(F.min("rep").alias("least"))
    labels = named.where("copies > 1 or root is not null").join(least, "root", "left").select("node", F.coalesce("least", "rep").alias("rep"))
    # A set that very many share is spread over SALTS.
    labels = labels.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    members = drawn.select("id", "print", "n", "node", F.when((F.col("n") > 0) & F.col("id").isNotNull(), F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int")).alias("salt"))
    first = F.col("rep").isNull() | ((F.col("rep.id") == F.col("id")) & (F.col("rep.print") == F.col("print")))
    return members.join(labels, ["node", "salt"], "left").select("id", "print", "n", F.coalesce("rep.id", "id").alias("component"), first.alias("first"))


def deduplicate(docs: DataFrame, id: str = "doc_id", text: str = "text", percent: int = 80) -> DataFrame:
    """The rows of docs, all columns as they are, without near duplicates: of each component the first (id, text) stays.

    So does every row without an id, and of rows that repeat an id and a text
    (null texts too) one; texts without words are linked with nothing.  An empty
    table gives an empty one.
    """
    gone = labelled(docs, id, text, percent).where("not first").select(F.col("id").alias("_i"), F.col("print").alias("_p")).distinct().alias("gone")
    print_ = fresh(docs, "print")
    rows = docs.withColumn(print_, F.xxhash64(F.col(f"`{text}`")))
    known, none = rows.where(F.col(f"`{id}`").isNotNull()), rows.where(F.col(f"`{id}`").isNull())
    known = known.alias("rows").join(gone, F.expr(f"cast(rows.`{id}` as bigint) = gone._i and rows.`{print_}` = gone._p"), "left_anti")
    return known.dropDuplicates([id, print_]).unionByName(none).select(*[F.col(f"`{c}`") for c in docs.columns])
