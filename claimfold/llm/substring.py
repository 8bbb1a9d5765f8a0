"""Substring dedup by fixed-block anchors.

A passage is a window of `WINDOW` words.  Every document is cut into reference
blocks of ANCHOR = (WINDOW + 1) / 2 words that do not overlap; each window then
holds one whole block of its document, and a document that repeats the window
holds the same words as one of its rolling ANCHOR-word windows.  So:

1. Every block and every rolling probe of a batch of texts is sent, as packed
   32-bit keys, to the bucket of its hash: once a batch, whatever number of its
   texts has it.  The bucket answers which keys a block and a probe of another
   document share: the anchors.  Keys are filters only.
2. Documents extend their anchors to all windows around them.  Of the documents
   of a batch that share a window, that of the smallest id sends it (96-bit hashes
   beside the bucket's bits) to be compared, the others have it as a repeat; the
   answer names the places whose words start in a document of a smaller id.
   Neighbouring windows overlap, so their union is the maximal exact repeat.
3. Texts drop the covered words.

Documents of equal word sequences are found first by digest and need no windows.
Texts move once (by a hash of the id; the exchange is used three times), keys as bytes.
No task holds more than a batch of texts or a bucket of keys, both sized from the
bytes of all texts; a passage in very many documents adds one key and one window a batch.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import settle, text_bytes_total
from .words import Words, chunks, mix64, powers, rolling, window_owner

WINDOW = 13
BATCH_BYTES, BUCKET_BYTES, SALTS = 6 << 20, 12 << 20, 32
_U32 = np.uint64(0xFFFFFFFF)
_SEQUENCE = 0xA0761D6478BD642F


def _sequence_digest(w: Words, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit digests of each text's word sequence."""
    within = np.arange(len(h)) - np.repeat(w.first[:-1], w.count)
    weight = powers(_SEQUENCE, int(w.count.max(initial=0)) + 1)[within]
    out = []
    for v in (h * weight, mix64(h + np.uint64(0x5851F42D4C957F2D)) * weight):
        sums = np.zeros(len(v) + 1, dtype=np.uint64)
        np.cumsum(v, out=sums[1:])
        out.append(mix64(sums[w.first[1:]] - sums[w.first[:-1]]).view(np.int64))
    return out[0], out[1]


def _pack(*arrays: np.ndarray) -> bytes:
    """Arrays as bytes, each with its length in front."""
    return b"".join(np.int64(a.nbytes).tobytes() + a.tobytes() for a in arrays)


def _unpack(data: bytes, *kinds: type) -> list[np.ndarray]:
    at, out = 0, []
    for k in kinds:
        n = int(np.frombuffer(data, np.int64, 1, at)[0])
        out.append(np.frombuffer(data, k, n // np.dtype(k).itemsize, at + 8))
        at += 8 + n
    return out


def _delta(a: np.ndarray) -> np.ndarray:
    return np.diff(a, prepend=a.dtype.type(0))


def _runs(a: np.ndarray) -> np.ndarray:
    """Starts of runs of equal values, and the length at the end."""
    return np.concatenate([np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))[: len(a)], [len(a)]])


def _live(w: Words, h: np.ndarray, ids: np.ndarray, known: np.ndarray, marked: set[tuple[int, int]]) -> np.ndarray:
    """Which texts are compared: those with an id that aren't copies."""
    if not marked:
        return known
    digest, _ = _sequence_digest(w, h)
    return known & np.array([pair not in marked for pair in zip(ids.tolist(), digest.tolist(), strict=True)], dtype=bool)


def _anchor_requests(n_buckets: int, anchor: int):
    """A batch of texts to (bucket, batch, its keys there, flags): a key once a batch, however many texts have it.

    The flags tell whether the key is a block somewhere in the batch, and whether two of its texts have it.
    """

    def run(docs: pa.Table) -> pa.Table:
        rows, marked = _ordered(docs)
        ids, known = _ids(rows)
        text, home = _texts(rows), docs.column("b")[0].as_py()
        keys, blocks, owners = [np.zeros(0, np.uint64)], [np.zeros(0, bool)], [np.zeros(0, np.int64)]
        for x, y in chunks(text):
            w = Words(text.slice(x, y - x))
            h = w.hashes()
            first, owner = window_owner(w, anchor)
            if not len(first):
                continue
            live = _live(w, h, ids[x:y], known[x:y], marked)[owner]
            first, owner = first[live], owner[live]
            keys.append(_bucketed(rolling(h, anchor)[first], n_buckets))
            blocks.append((first - w.first[owner]) % anchor == 0)
            owners.append(x + owner)
        key, block, owner = np.concatenate(keys), np.concatenate(blocks), np.concatenate(owners)
        order = np.argsort(key, kind="stable")  # a key's texts stay in their order
        key, block, owner = key[order], block[order], owner[order]
        cut = _runs(key)
        key, several = key[cut[:-1]], owner[cut[:-1]] != owner[cut[1:] - 1]
        block = np.logical_or.reduceat(block, cut[:-1]) if len(key) else block
        bucket = (key >> np.uint64(32)).astype(np.int32)
        cut = _runs(bucket)
        pieces = list(zip(cut[:-1], cut[1:], strict=True))
        return pa.table(
            {
                "bucket": pa.array(bucket[cut[:-1]], pa.int32()),
                "b": pa.array([home] * len(pieces), pa.int32()),
                "key": pa.array([(key[s:e] & _U32).astype(np.uint32).tobytes() for s, e in pieces], pa.binary()),
                "flags": pa.array([np.packbits(np.concatenate([block[s:e], several[s:e]])).tobytes() for s, e in pieces], pa.binary()),
            }
        )

    return run


def _anchor_answers(table: pa.Table) -> pa.Table:
    """Which keys of a bucket are anchors, for each home that has them: a block somewhere, and two texts that share it."""
    keys = [np.frombuffer(k, np.uint32) for k in table.column("key").to_pylist()]
    flags = [np.unpackbits(np.frombuffer(f, np.uint8), count=2 * len(k)).astype(bool) for k, f in zip(keys, table.column("flags").to_pylist(), strict=True)]
    home = np.repeat(table.column("b").to_numpy(), [len(k) for k in keys])
    block = np.concatenate([f[: len(k)] for k, f in zip(keys, flags, strict=True)])
    several = np.concatenate([f[len(k) :] for k, f in zip(keys, flags, strict=True)])
    keys = np.concatenate(keys)
    order = np.argsort(keys, kind="stable")
    keys, home = keys[order], home[order]
    cut = _runs(keys)
    size = np.diff(cut)
    anchor = np.logical_or.reduceat(block[order], cut[:-1]) & ((size > 1) | np.logical_or.reduceat(several[order], cut[:-1]))
    hit = np.repeat(anchor, size)
    keys, home = keys[hit], home[hit]
    order = np.argsort(home, kind="stable")
    keys, home = keys[order], home[order]
    cut = _runs(home)
    bucket = table.column("bucket")[0].as_py()
    return pa.table(
        {
            "b": pa.array(home[cut[:-1]], pa.int32()),
            "bucket": pa.array([bucket] * (len(cut) - 1), pa.int32()),
            "payload": pa.array([_pack(keys[s:e]) for s, e in zip(cut[:-1], cut[1:], strict=True)], pa.binary()),
        }
    )


def _ordered(docs: pa.Table) -> tuple[pa.Table, np.ndarray, list[tuple[int, int, int]]]:
    """Texts of a batch in the order of (id, text), those that are copies, and the ids' bounds.

    A row without text but with a digest marks the texts of its id and digest as copies.
    """
    mark = docs.column("copy_of").to_numpy(zero_copy_only=False)
    is_mark = ~np.isnan(mark.astype(float)) if mark.dtype != object else np.array([m is not None for m in mark])
    marks = docs.filter(pa.array(is_mark))
    rows = docs.filter(pa.array(~is_mark)).sort_by([("id", "ascending"), ("text", "ascending")])
    marked = set(zip(marks.column("id").to_pylist(), marks.column("copy_of").to_pylist(), strict=True))
    return rows, marked


def _ids(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids, -1 for a null, and which are known."""
    return rows.column("id").fill_null(-1).to_numpy(), rows.column("id").is_valid().to_numpy()


def _bucketed(key: np.ndarray, n_buckets: int) -> np.ndarray:
    """The bucket of a 64-bit key above its lower half."""
    return ((key >> np.uint64(32)).astype(np.int64) % n_buckets).astype(np.uint64) << np.uint64(32) | (key & _U32)


def _texts(rows: pa.Table) -> pa.Array:
    text = rows.column("text").combine_chunks()
    return text if not isinstance(text, pa.ChunkedArray) else (text.chunk(0) if text.num_chunks else pa.array([], pa.string()))


def _window_requests(n_buckets: int, anchor: int, window: int):
    """(batch of texts, its anchors) to (bucket, packed windows around anchors).

    Of the texts of a batch that share a window only those of the smallest id ask
    the bucket; the places of the others are repeats, and go home as bucket -1 - batch.
    """

    def run(docs: pa.Table, answers: pa.Table) -> pa.Table:
        none = pa.table({"bucket": pa.array([], pa.int32()), "payload": pa.array([], pa.binary())})
        if not docs.num_rows or not answers.num_rows:
            return none
        keys = [np.uint64(bucket) << np.uint64(32) | _unpack(p, np.uint32)[0].astype(np.uint64) for bucket, p in zip(answers.column("bucket").to_pylist(), answers.column("payload").to_pylist(), strict=True)]
        anchors = np.sort(np.concatenate(keys))
        rows, marked = _ordered(docs)
        ids, known = _ids(rows)
        home, text = docs.column("b")[0].as_py(), _texts(rows)
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint32))]
        for x, y in chunks(text):
            w = Words(text.slice(x, y - x))
            h = w.hashes()
            first, owner = window_owner(w, anchor)
            if not len(first):
                continue
            key = _bucketed(rolling(h, anchor)[first], n_buckets)
            at = np.minimum(np.searchsorted(anchors, key), len(anchors) - 1)
            hits = np.zeros(len(w.start) + 1, dtype=np.int64)
            hits[1:][first[(anchors[at] == key) & _live(w, h, ids[x:y], known[x:y], marked)[owner]]] = 1
            hits = np.cumsum(hits)
            start, owner = window_owner(w, window)
            near = hits[start + window - anchor + 1] > hits[start]
            start, owner = start[near], owner[near]
            found.append((x + owner, start - w.first[owner], rolling(h, window)[start], (rolling(h, window, seed=31)[start] & _U32).astype(np.uint32)))
        local, place, long, check = (np.concatenate([f[k] for f in found]) for k in range(4))
        order = np.lexsort((check, long))  # a window's texts stay in the order of their ids
        local, place, long, check = local[order], place[order], long[order], check[order]
        cut = np.append(np.flatnonzero(np.append([True], (long[1:] != long[:-1]) | (check[1:] != check[:-1])))[: len(long)], len(long))
        who = ids[local]
        here = who > np.repeat(who[cut[:-1]], np.diff(cut))  # a smaller id of this batch has it
        buckets, payloads = [], []
        if here.any():
            at = np.flatnonzero(here)[np.lexsort((place[here], local[here]))]
            buckets.append(-1 - home)
            payloads.append(_pack(local[at].astype(np.int32), place[at].astype(np.uint32)))
        bucket = (mix64(long + np.uint64(0x632BE59BD9B4E019)) >> np.uint64(16)).astype(np.int64) % n_buckets
        at = np.flatnonzero(~here)
        at = at[np.lexsort((place[at], local[at], bucket[at]))]
        local, place, long, check, bucket = (v[at] for v in (local, place, long, check, bucket))
        cut = _runs(bucket)
        for s, e in zip(cut[:-1], cut[1:], strict=True):
            doc = _runs(local[s:e])
            who = local[s:e][doc[:-1]]
            buckets.append(int(bucket[s]))
            payloads.append(_pack(np.array([home], np.int32), _delta(ids[who]), who.astype(np.int32), np.diff(doc).astype(np.uint32), place[s:e].astype(np.uint32), long[s:e], check[s:e]))
        return pa.table({"bucket": pa.array(buckets, pa.int32()), "payload": pa.array(payloads, pa.binary())})

    return run


def _window_answers(table: pa.Table) -> pa.Table:
    """Places of a bucket's windows that start in a document of a smaller id, for each home."""
    bucket = table.column("bucket")[0].as_py()
    if bucket < 0:  # already decided within a batch
        return pa.table({"b": pa.array([-1 - bucket] * table.num_rows, pa.int32()), "payload": table.column("payload")})
    parts = []
    for payload in table.column("payload").to_pylist():
        home, i, local, n, place, long, check = _unpack(payload, np.int32, np.int64, np.int32, np.uint32, np.uint32, np.uint64, np.uint32)
        parts.append((np.repeat(home, len(place)), np.repeat(np.cumsum(i), n), np.repeat(local, n), place, long, check))
    home, ids, local, place, long, check = (np.concatenate([p[k] for p in parts]) for k in range(6))
    order = np.lexsort((check, long))
    long, check, ids = long[order], check[order], ids[order]
    new = np.concatenate([[True], (long[1:] != long[:-1]) | (check[1:] != check[:-1])])
    cut = np.concatenate([np.flatnonzero(new), [len(long)]])
    gone = order[ids > np.repeat(np.minimum.reduceat(ids, cut[:-1]), np.diff(cut))]
    gone = gone[np.lexsort((place[gone], local[gone], home[gone]))]
    home, local, place = home[gone], local[gone], place[gone]
    cut = _runs(home)
    return pa.table(
        {
            "b": pa.array(home[cut[:-1]], pa.int32()),
            "payload": pa.array([_pack(local[s:e], place[s:e]) for s, e in zip(cut[:-1], cut[1:], strict=True)], pa.binary()),
        }
    )


def _drop_words(window: int, extra: list[str]):
    """(batch of texts, places of repeats) to the texts without the covered words."""

    def run(docs: pa.Table, answers: pa.Table) -> pa.Table:
        rows, marked = _ordered(docs)
        text, ids = _texts(rows), rows.column("id").to_pylist()
        local, place = [np.zeros(0, np.int32)], [np.zeros(0, np.uint32)]
        for p in answers.column("payload").to_pylist():
            l, s = _unpack(p, np.int32, np.uint32)
            local.append(l)
            place.append(s)
        local, place = np.concatenate(local), np.concatenate(place).astype(np.int64)
        order = np.argsort(local, kind="stable")
        local, place = local[order], place[order]
        n_words, n_removed, kept = [], [], []
        for x, y in chunks(text):
            part = text.slice(x, y - x)
            w = Words(part)
            digest, _ = _sequence_digest(w, w.hashes())
            s, e = np.searchsorted(local, [x, y])
            turn = np.zeros(len(w.start) + 1, dtype=np.int64)
            at = w.first[local[s:e] - x] + place[s:e]
            np.add.at(turn, at, 1)
            np.add.at(turn, at + window, -1)
            gone = np.cumsum(turn)[:-1] > 0
            for i in range(w.n_docs):
                if (ids[x + i], int(digest[i])) in marked:
                    gone[w.first[i] : w.first[i + 1]] = True
            sums = np.concatenate([[0], np.cumsum(gone)])
            removed = sums[w.first[1:]] - sums[w.first[:-1]]
            raw, stay = w.raw.tobytes(), ~gone
            for i in range(w.n_docs):
                words = raw[w.doc_start[i] : w.doc_start[i + 1]].split()
                if removed[i]:
                    words = [words[j] for j in np.flatnonzero(stay[w.first[i] : w.first[i + 1]]).tolist()]
                kept.append(b" ".join(words))
            n_words.append(w.count.astype(np.int64))
            n_removed.append(removed.astype(np.int64))
        join = lambda parts: pa.array(np.concatenate([np.zeros(0, np.int64), *parts]))
        return pa.table({"id": rows.column("id"), "n_words": join(n_words), "n_removed": join(n_removed), "kept_text": pa.array(kept, pa.binary()).cast(pa.string()), **{c: rows.column(c) for c in extra}})

    return run


def remove_repeats(docs: DataFrame, id: str = "doc_id", text: str = "text", window: int = WINDOW, keep: tuple[str, ...] = (), kept: str | None = None) -> DataFrame:
    """(id, n_words, n_removed, kept_text, columns of `keep`) for every row of docs.

    With `kept` the result is the id, the columns of `keep` and the kept text under that name alone.

    A word goes if a window of `window` words (odd, 3 or more) covers it whose
    words also start in a document of a smaller id; windows are judged on the
    input.  kept_text has the other words, joined by one blank.  A null text
    counts as empty, and what has fewer words than a window stays whole.  A row
    without an id stays whole and takes from none.  Rows that share an id are
    compared with other ids only.
    """
    if window < 3 or window % 2 == 0:
        raise ValueError("window must be odd and 3 or more")
    anchor = (window + 1) // 2
    total = text_bytes_total(docs, text)
    homes, buckets = max(1, -(-total // BATCH_BYTES)), max(1, -(-total // BUCKET_BYTES))
    extra = [f"_x{k}" for k in range(len(keep))]
    base = docs.select(
        F.col(id).cast("long").alias("id"), F.col(text).alias("text"), F.pmod(F.xxhash64(F.col(id).cast("long")), F.lit(homes)).cast("int").alias("b"), *[F.col(f"`{c}`").alias(x) for c, x in zip(keep, extra, strict=True)]
    )

    def digests(batches):
        for b in batches:
            got = []
            for x, y in chunks(b.column("text")):
                w = Words(b.column("text").slice(x, y - x))
                got.append((w.count.astype(np.int64), *_sequence_digest(w, w.hashes())))
            cols = [np.concatenate([np.zeros(0, np.int64), *(g[k] for g in got)]) for k in range(3)]
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("b"), *map(pa.array, cols)], names=["id", "b", "n", "d1", "d2"])

    slim = base.select("id", "b", "text").mapInArrow(digests, "id long, b int, n long, d1 long, d2 long").where(f"n >= {window} and id is not null")
    slim = settle(slim, "substring-digests")
    groups = slim.groupBy("n", "d1", "d2").agg(F.min("id").alias("lead"), F.max("id").alias("last")).where("lead <> last")
    groups = groups.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    copies = slim.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int")).join(groups, ["n", "d1", "d2", "salt"]).where("id > lead")
    copies = settle(copies.select("b", "id", F.col("d1").alias("copy_of")).distinct(), "substring-copies")

    fields = {f.name: f.dataType for f in base.schema.fields}
    marks = copies.select("id", F.lit(None).cast("string").alias("text"), "b", *[F.lit(None).cast(fields[x]).alias(x) for x in extra], "copy_of")
    inbox = base.withColumn("copy_of", F.lit(None).cast("long")).union(marks).groupBy("b")
    asked = inbox.applyInArrow(_anchor_requests(buckets, anchor), "bucket int, b int, key binary, flags binary")
    anchors = asked.groupBy("bucket").applyInArrow(_anchor_answers, "b int, bucket int, payload binary")
    windows = inbox.cogroup(anchors.groupBy("b")).applyInArrow(_window_requests(buckets, anchor, window), "bucket int, payload binary")
    places = windows.groupBy("bucket").applyInArrow(_window_answers, "b int, payload binary")
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_text", T.StringType()), *[T.StructField(x, fields[x]) for x in extra]])
    out = inbox.cogroup(places.groupBy("b")).applyInArrow(_drop_words(window, extra), schema)
    if kept is not None:
        return out.select(F.col("id").cast(docs.schema[id].dataType).alias(id), F.col("kept_text").alias(kept), *[F.col(x).alias(c) for c, x in zip(keep, extra, strict=True)])
    return out.select(F.col("id").alias(id), "n_words", "n_removed", "kept_text", *[F.col(x).alias(c) for c, x in zip(keep, extra, strict=True)])
