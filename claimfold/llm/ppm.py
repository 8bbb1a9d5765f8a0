"""Prediction by partial matching over bytes, with symbol exclusion, trained on the whole corpus.

What is coded is the same as the unigram base codes: the words in lower case (A
to Z), here byte by byte with a blank between, and the end.

The context trie has the last ORDER bytes of every training place.  A byte is
coded at the longest context seen; where it is new there, an escape is coded and
the next shorter context tries, without the symbols that the longer one has seen.
As counts of all orders come from one corpus, what a context has seen is a subset
of what its suffix has seen, so exclusion needs two sums a context only: how many
symbols it has seen, and how often its suffix has seen those.

The trie is never in one place.  Texts lie in batches by a hash of the id.  Each
batch sends the distinct (context, byte) pairs it has, with its training counts,
to the bucket of the last three context bytes; the bucket adds up the counts and
answers the code length of every pair asked for.  Only orders 0 to 2 go to all
tasks: 256 ** 3 counts at most, whatever the corpus.  Word counts for the
unigram base travel the same way.  What moves grows with the corpus, and so does
the number of buckets; a word or pair that every text has is one entry a batch.

`Trie` is the model in plain Python: the adaptive mode, and what tests compare with.
"""

from __future__ import annotations

import math
import uuid
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import settle, spread, text_bytes_total
from .words import Words, chunks, mix64

ORDER = 4
#: Bytes that UTF-8 never has: before a text, and its end, which is coded like a byte.
PAD, END = 0xFF, 0xFE
SYMBOLS = 255
BATCH_BYTES, PLACES = 3 << 20, 23
#: A bucket gets the pairs of about so much text.
BUCKET_BYTES = 32 << 20
END_TOKEN = mix64(np.array([0x1D8AF066], dtype=np.uint64))[0]


def _odds(n, total, kinds, escape: str):
    """Probabilities (of a symbol seen n times, of an escape) in a context of so many events and symbols."""
    if escape == "a":
        return n / (total + 1), 1 / (total + 1)
    if escape == "d":
        return (2 * n - 1) / (2 * total), kinds / (2 * total)
    return n / (total + kinds), kinds / (total + kinds)


class Trie:
    """Counts of every context up to `order` bytes, in plain Python."""

    def __init__(self, order: int = ORDER, escape: str = "c"):
        self.order, self.escape = order, escape
        self.seen: dict[bytes, dict[int, int]] = defaultdict(dict)

    def add(self, context: bytes, symbol: int) -> None:
        for k in range(self.order + 1):
            node = self.seen[context[len(context) - k :]]
            node[symbol] = node.get(symbol, 0) + 1

    def log10(self, context: bytes, symbol: int) -> float:
        out, excluded = 0.0, set()
        for k in range(self.order, -1, -1):
            node = {s: n for s, n in self.seen.get(context[len(context) - k :], {}).items() if s not in excluded}
            if not node:
                continue
            p, e = _odds(node.get(symbol, 0), sum(node.values()), len(node), self.escape)
            if symbol in node:
                return out + math.log10(p)
            out += math.log10(e)
            excluded |= set(node)
        return out - math.log10(max(1, SYMBOLS - len(excluded)))

    def places(self, text: str | None):
        data = bytes([PAD]) * self.order + b" ".join((text or "").encode().lower().split()) + bytes([END])
        for i in range(self.order, len(data)):
            yield data[i - self.order : i], data[i]

    def learn(self, text: str | None) -> None:
        for context, symbol in self.places(text):
            self.add(context, symbol)

    def score(self, text: str | None) -> float:
        return sum(self.log10(c, s) for c, s in self.places(text))

    def adaptive(self, text: str | None) -> float:
        """Code length of a text while it is learnt, byte by byte."""
        out = 0.0
        for context, symbol in self.places(text):
            out += self.log10(context, symbol)
            self.add(context, symbol)
        return out


def adaptive_scores(docs: DataFrame, id: str = "doc_id", text: str = "text", order: int = ORDER, escape: str = "c") -> DataFrame:
    """(id, n_bytes, score): log10 probability of each text under a model that starts empty with it."""

    def run(batches):
        for b in batches:
            texts = b.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len((t or "").encode()) for t in texts], pa.int64()), pa.array([Trie(order, escape).adaptive(t) for t in texts], pa.float64())], names=[id, "n_bytes", "score"])

    return docs.select(id, text).mapInArrow(run, f"`{id}` {docs.schema[id].dataType.simpleString()}, n_bytes long, score double")


def normal_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased words joined by one blank, and END, of all texts in a row; and each text's start."""
    parts, sizes = [np.zeros(0, np.uint8)], [np.zeros(1, np.int64)]
    for x, y in chunks(column):
        raw, start = _normal_chunk(column.slice(x, y - x))
        parts.append(raw)
        sizes.append(np.diff(start))
    return np.concatenate(parts), np.cumsum(np.concatenate(sizes))


def _normal_chunk(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    w = Words(column, lower=True)
    turn = np.zeros(len(w.bytes) + 1, dtype=np.int8)
    turn[w.start] += 1
    turn[w.end] -= 1
    keep = np.cumsum(turn)[:-1].astype(bool)
    keep[w.end] = True  # one blank after each word
    close = w.doc_start[1:] - 1
    close[w.count > 0] = w.end[w.first[1:][w.count > 0] - 1]
    keep[close] = True
    out = np.where(keep, w.bytes, 0)
    out[w.end] = 0x20
    out[close] = END
    ends = np.cumsum(keep)[close]
    return out[keep], np.concatenate([[0], ends])


def _events(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Codes of all coded places: the last four bytes, latest first, then the byte; and each text's first place."""
    raw, start = normal_bytes(column)
    code, size = np.zeros(len(raw), dtype=np.uint64), np.diff(start)
    for k in range(1, ORDER + 1):
        back = np.empty_like(raw)
        back[k:], back[:k] = raw[:-k], PAD
        for j in range(k):  # what lies before a text's start
            back[(start[:-1] + j)[size > j]] = PAD
        code <<= np.uint64(8)
        code |= back
    code <<= np.uint64(8)
    code |= raw
    return code, start


def _low_orders(batches):
    """Counts of (two last bytes, byte) of training texts."""
    for b in batches:
        text = b.column(0)
        found = [np.zeros((2, 0), np.int64)]
        for x, y in chunks(text):
            code, _ = _events(text.slice(x, y - x))
            keys, n = np.unique((code >> np.uint64(24)) << np.uint64(8) | (code & np.uint64(255)), return_counts=True)
            found.append(np.stack([keys.astype(np.int64), n]))
        keys, n = np.concatenate(found, axis=1)
        keys, at = np.unique(keys, return_inverse=True)
        yield pa.RecordBatch.from_arrays([pa.array(keys.astype(np.int32)), pa.array(np.bincount(at, weights=n, minlength=len(keys)).astype(np.int64))], names=["key", "n"])


class Low:
    """Orders 0 to 2 with totals, kinds and, for exclusion, what the suffix has of the symbols seen."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray):
        # key is (last, last but one, byte); rows are the pairs seen, 65,536 at most, and one of zeros
        pairs, at = np.unique(keys >> 8, return_inverse=True)
        self.row = np.full(1 << 16, len(pairs), dtype=np.int64)
        self.row[pairs] = np.arange(len(pairs))
        self.n2, last = np.zeros((len(pairs) + 1, 256)), pairs >> 8
        self.n2[at, keys & 255] = counts
        self.n1 = np.zeros((256, 256))
        np.add.at(self.n1, last, self.n2[:-1])
        self.n0 = self.n1.sum(axis=0)
        self.t2, self.d2 = self.n2.sum(axis=1), (self.n2 > 0).sum(axis=1)
        self.t1, self.d1 = self.n1.sum(axis=1), (self.n1 > 0).sum(axis=1)
        self.t0, self.d0 = self.n0.sum(), int((self.n0 > 0).sum())
        self.e2 = np.append(((self.n2[:-1] > 0) * self.n1[last]).sum(axis=1), 0.0)
        self.e1 = ((self.n1 > 0) * self.n0[None, :]).sum(axis=1)


_low: dict[str, Low] = {}


def _code_lengths(code: np.ndarray, count: np.ndarray, low: Low, escape: str) -> np.ndarray:
    """log10 of the probability of each (context, byte); codes are sorted, distinct and hold whole contexts."""

    def groups(of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        new = np.ones(len(of), dtype=bool)
        new[1:] = of[1:] != of[:-1]
        return np.flatnonzero(new), np.cumsum(new) - 1

    s = (code & np.uint64(255)).astype(np.int64)
    c1, c2 = (code >> np.uint64(32)).astype(np.int64), (code >> np.uint64(24) & np.uint64(255)).astype(np.int64)
    n4 = count.astype(np.float64)
    at4, of4 = groups(code >> np.uint64(8))
    three = (code >> np.uint64(16)) << np.uint64(8) | s.astype(np.uint64)
    order = np.argsort(three, kind="stable")
    at3s, of3s = groups(three[order])
    n3s = np.add.reduceat(n4[order], at3s)
    n3 = np.empty(len(code))
    n3[order] = n3s[of3s]
    u3 = three[order][at3s]  # distinct (three bytes, byte)
    at3, of3 = groups(u3 >> np.uint64(8))
    a, b, z = (u3 >> np.uint64(24)).astype(np.int64), (u3 >> np.uint64(16) & np.uint64(255)).astype(np.int64), (u3 & np.uint64(255)).astype(np.int64)
    # n2 is known for whole contexts; a symbol seen after three bytes has n3 > 0.
    t3, d3, e3 = (np.add.reduceat(v, at3) for v in (n3s, (n3s > 0) * 1.0, (n3s > 0) * low.n2[low.row[a << 8 | b], z]))
    back = np.empty(len(code), dtype=np.int64)
    back[order] = of3[of3s]
    t4, d4, e4 = (np.add.reduceat(v, at4)[of4] for v in (n4, (n4 > 0) * 1.0, (n4 > 0) * n3))
    t3, d3, e3 = t3[back], d3[back], e3[back]
    row = low.row[c1 << 8 | c2]
    levels = [
        (n4, t4, d4),
        (n3, t3 - e4, d3 - d4),
        (low.n2[row, s], low.t2[row] - e3, low.d2[row] - d3),
        (low.n1[c1, s], low.t1[c1] - low.e2[row], low.d1[c1] - low.d2[row]),
        (low.n0[s], low.t0 - low.e1[c1], low.d0 - low.d1[c1]),
    ]
    out, open_ = np.zeros(len(code)), np.ones(len(code), dtype=bool)
    with np.errstate(divide="ignore", invalid="ignore"):
        for n, total, kinds in levels:
            able = open_ & (kinds > 0.5)
            p, e = _odds(n, total, kinds, escape)
            hit = able & (n > 0)
            out += np.where(hit, np.log10(p), np.where(able, np.log10(e), 0.0))
            open_ &= ~hit
    return np.where(open_, out - math.log10(max(1, SYMBOLS - low.d0)), out)


def _runs(a: np.ndarray) -> np.ndarray:
    return np.concatenate([np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))[: len(a)], [len(a)]])


class Batch:
    """Distinct pairs and words of a batch of texts, with their places."""

    def __init__(self, docs: pa.Table, buckets: int):
        text = docs.column("text").combine_chunks()
        self.text = text.chunk(0) if isinstance(text, pa.ChunkedArray) else text
        held = np.asarray(docs.column("held_out").to_numpy(), dtype=bool)
        code, self.start = _events(self.text)
        train = np.repeat(~held, np.diff(self.start))
        n = len(code)
        if n < 1 << PLACES:  # one sort of pair and place together
            code <<= np.uint64(PLACES)
            code |= np.arange(n, dtype=np.uint64)
            code.sort()
            self.place = (code & np.uint64((1 << PLACES) - 1)).astype(np.int32)
            code >>= np.uint64(PLACES)
        else:
            self.place = np.argsort(code, kind="stable")
            code = code[self.place]
        cut = _runs(code)
        self.size, self.code = np.diff(cut), code[cut[:-1]]
        self.count = np.add.reduceat(train[self.place].astype(np.int64), cut[:-1]) if n else np.zeros(0, np.int64)
        self.bucket = (mix64(self.code >> np.uint64(16)) % np.uint64(buckets)).astype(np.int64)
        hashes, owner = [], []
        self.n_tokens = np.zeros(len(held), dtype=np.int64)
        for x, y in chunks(self.text):
            w = Words(self.text.slice(x, y - x), lower=True)
            hashes += [w.hashes(), np.full(y - x, END_TOKEN, dtype=np.uint64)]
            owner += [x + w.owner(), np.arange(x, y)]
            self.n_tokens[x:y] = w.count + 1
        hashes, self.owner = np.concatenate([np.zeros(0, np.uint64), *hashes]), np.concatenate([np.zeros(0, np.int64), *owner])
        self.word, self.word_at = np.unique(hashes, return_inverse=True)
        self.word_count = np.bincount(self.word_at, weights=~held[self.owner], minlength=len(self.word)).astype(np.int64)
        self.word_bucket = ((self.word >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)


def _requests(buckets: int):
    def run(docs: pa.Table) -> pa.Table:
        home, batch, rows = docs.column("b")[0].as_py(), Batch(docs, buckets), []
        for kind, bucket, key, count in ((0, batch.bucket, batch.code, batch.count), (1, batch.word_bucket, batch.word, batch.word_count)):
            order = np.argsort(bucket, kind="stable")
            cut = _runs(bucket[order])
            for s, e in zip(cut[:-1], cut[1:], strict=True):
                at = order[s:e]
                rows.append((kind, int(bucket[at[0]]), home, np.diff(key[at], prepend=np.uint64(0)).tobytes(), count[at].astype(np.uint32).tobytes()))
        columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
        return pa.table({n: pa.array(list(c), t) for n, c, t in zip(("kind", "bucket", "b", "key", "n"), columns, (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)})

    return run


def _answers(low, escape: str):
    token = uuid.uuid4().hex

    def run(asked: pa.Table) -> pa.Table:
        kind = asked.column("kind")[0].as_py()
        homes = asked.column("b").to_pylist()
        keys = [np.cumsum(np.frombuffer(k, np.uint64), dtype=np.uint64) for k in asked.column("key").to_pylist()]
        counts = [np.frombuffer(n, np.uint32) for n in asked.column("n").to_pylist()]
        whole, at = np.unique(np.concatenate(keys), return_inverse=True)
        count = np.bincount(at, weights=np.concatenate(counts), minlength=len(whole))
        if kind == 0:
            if token not in _low:  # built once in each Python worker
                _low.clear()
                _low[token] = Low(*low.value)
            answer = _code_lengths(whole, count, _low[token], escape)
        else:
            answer = count.astype(np.float64)
        answer = answer[at]
        ends = np.cumsum([len(k) for k in keys])
        parts = [answer[e - len(k) : e] for e, k in zip(ends, keys, strict=True)]
        stats = (float(count.sum()), float((count > 0).sum())) if kind == 1 else (0.0, 0.0)
        return pa.table(
            {
                "b": pa.array([*homes, -1], pa.int32()),
                "kind": pa.array([kind] * (len(homes) + 1), pa.int32()),
                "bucket": pa.array([asked.column("bucket")[0].as_py()] * (len(homes) + 1), pa.int32()),
                "answer": pa.array([*((p if kind == 0 else p.astype(np.uint32)).tobytes() for p in parts), b""], pa.binary()),
                "tokens": pa.array([*[0.0] * len(homes), stats[0]]),
                "kinds": pa.array([*[0.0] * len(homes), stats[1]]),
            }
        )

    return run


def _scores(buckets: int):
    def run(docs: pa.Table, answers: pa.Table) -> pa.Table:
        empty = pa.array([], pa.int64())
        if not docs.num_rows:
            return pa.table({"id": empty, "held_out": pa.array([], pa.bool_()), "n_tokens": empty, "n_known": empty, "log_counts": pa.array([], pa.float64()), "score": pa.array([], pa.float64())})
        batch = Batch(docs, buckets)
        length, known = np.zeros(len(batch.code)), np.zeros(len(batch.word))
        for kind, bucket, answer in zip(*(answers.column(c).to_pylist() for c in ("kind", "bucket", "answer")), strict=True):
            if kind == 0:
                length[batch.bucket == bucket] = np.frombuffer(answer, np.float64)
            else:
                known[batch.word_bucket == bucket] = np.frombuffer(answer, np.uint32)
        per_place = np.empty(len(batch.place))
        per_place[batch.place] = np.repeat(length, batch.size)
        per_word = known[batch.word_at]
        n = docs.num_rows
        return pa.table(
            {
                "id": docs.column("id"),
                "held_out": docs.column("held_out"),
                "n_tokens": pa.array(batch.n_tokens),
                "n_known": pa.array(np.bincount(batch.owner, weights=per_word > 0, minlength=n).astype(np.int64)),
                "log_counts": pa.array(np.bincount(batch.owner, weights=np.log10(per_word + 1), minlength=n)),
                "score": pa.array(np.add.reduceat(per_place, batch.start[:-1])),
            }
        )

    return run


def score_documents(docs: DataFrame, held_out: Column, id: str = "doc_id", text: str = "text", escape: str = "d") -> DataFrame:
    """(id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row of docs.

    Rows where held_out is false or null are learnt from; all are scored.  Scores
    are log10 probabilities of whole texts with their end.  base_score is the
    add-one unigram model over lower-cased words.  A null text counts as empty
    and has its end alone.  escape is the estimator: "a", "c" or "d".
    """
    sc = docs.sparkSession.sparkContext
    total = text_bytes_total(docs, text)
    batches = max(1, -(-total // BATCH_BYTES))
    buckets = max(4 * spread(docs), -(-total // BUCKET_BYTES))
    base = docs.select(F.col(id).cast("long").alias("id"), F.col(text).alias("text"), F.coalesce(held_out, F.lit(False)).alias("held_out"), F.pmod(F.xxhash64(F.col(id).cast("long")), F.lit(batches)).cast("int").alias("b"))
    counts = base.where("not held_out").select("text").mapInArrow(_low_orders, "key int, n long").groupBy("key").agg(F.sum("n").alias("n")).toArrow()
    low = sc.broadcast((counts.column("key").to_numpy(), counts.column("n").to_numpy()))
    asked = base.groupBy("b").applyInArrow(_requests(buckets), "kind int, bucket int, b int, key binary, n binary")
    answers = settle(asked.groupBy("kind", "bucket").applyInArrow(_answers(low, escape), "b int, kind int, bucket int, answer binary, tokens double, kinds double"), "ppm-answers")
    sums = answers.where("b < 0").agg(F.coalesce(F.sum("tokens"), F.lit(0.0)).alias("tokens"), F.coalesce(F.sum("kinds"), F.lit(0.0)).alias("kinds")).first()
    out = base.groupBy("b").cogroup(answers.where("b >= 0").select("b", "kind", "bucket", "answer").groupBy("b")).applyInArrow(_scores(buckets), "id long, held_out boolean, n_tokens long, n_known long, log_counts double, score double")
    level = math.log10(sums["tokens"] + sums["kinds"] + 1)
    return out.select(F.col("id").alias(id), "held_out", "n_tokens", "n_known", F.lit(int(sums["tokens"])).cast("long").alias("train_tokens"), (F.col("log_counts") - F.col("n_tokens") * F.lit(level)).alias("base_score"), "score")
