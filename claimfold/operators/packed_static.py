"""Static features of a batch's candidates over arrays: those that `resolver._static` has, text work once a distinct text.

Texts are code points side by side.  A piece (three code points, or a word) is
hashed once a batch, by the hash that `features.hash_embedding` uses.
"""

from __future__ import annotations

import unicodedata

import numpy as np
import pyarrow as pa

#: Constants of the 64-bit hash, and the seed that Spark gives it.
_P1, _P2, _P3, _P4, _P5 = (np.uint64(v) for v in (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261))
_SEED, _ZERO = np.uint64(42), np.uint64(0)
#: Sets of numbers up to this are marked in a table instead of sorted.
_TABLE = 1 << 22


def _turned(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def _mixed(acc, lane: np.ndarray) -> np.ndarray:
    return _turned(acc + lane * _P2, 31) * _P1


def xxhash64(words: list[bytes]) -> np.ndarray:
    """Spark's xxhash64 of byte strings, those of a length at once."""
    out, size = np.empty(len(words), np.uint64), np.array([len(w) for w in words], dtype=np.int64)
    with np.errstate(over="ignore"):
        for n in np.unique(size).tolist():
            at = np.flatnonzero(size == n)
            raw = np.frombuffer(b"".join([words[i] for i in at.tolist()]), np.uint8).reshape(len(at), n)
            lane = lambda lo, kind, raw=raw: np.ascontiguousarray(raw[:, lo : lo + np.dtype(kind).itemsize]).view(kind)[:, 0].astype(np.uint64)
            h = np.full(len(at), _SEED + _P5)
            if n >= 32:
                v = [np.full(len(at), x) for x in (_SEED + _P1 + _P2, _SEED + _P2, _SEED, _SEED - _P1)]
                for lo in range(0, n // 32 * 32, 32):
                    v = [_mixed(x, lane(lo + 8 * i, "<u8")) for i, x in enumerate(v)]
                h = _turned(v[0], 1) + _turned(v[1], 7) + _turned(v[2], 12) + _turned(v[3], 18)
                for x in v:
                    h = (h ^ _mixed(_ZERO, x)) * _P1 + _P4
            h = h + np.uint64(n)
            lo = n // 32 * 32
            for lo in range(lo, n // 8 * 8, 8):
                h = _turned(h ^ _mixed(_ZERO, lane(lo, "<u8")), 27) * _P1 + _P4
            lo = n // 8 * 8
            if lo + 4 <= n:
                h = _turned(h ^ lane(lo, "<u4") * _P1, 23) * _P2 + _P3
                lo += 4
            for i in range(lo, n):
                h = _turned(h ^ lane(i, "u1") * _P5, 11) * _P1
            h = (h ^ (h >> np.uint64(33))) * _P2
            h = (h ^ (h >> np.uint64(29))) * _P3
            out[at] = h ^ (h >> np.uint64(32))
    return out.view(np.int64)


def _distinct(x: np.ndarray, below: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct numbers of x, all of 0 .. below - 1, and the place of each number among them."""
    if below > _TABLE:
        return np.unique(x, return_inverse=True)
    have = np.zeros(below, bool)
    have[x] = True
    keys = np.flatnonzero(have)
    place = np.empty(below, np.int32)
    place[keys] = np.arange(len(keys), dtype=np.int32)
    return keys, place[x]


class Texts:
    """Texts as code points, a '^' before and a '$' after each."""

    def __init__(self, texts: list[str]):
        self.n, self.joined = len(texts), "".join([f"^{t}$" for t in texts])
        points = np.frombuffer(self.joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        self.size = np.array([len(t) + 2 for t in texts], dtype=np.int64)
        self.row = np.repeat(np.arange(self.n, dtype=np.int64), self.size)
        letters, self.code = _distinct(points.astype(np.int64), 1 << 21)
        self.letters = [chr(c) for c in letters.tolist()]
        #: 0 for a letter, 1 for a digit, 2 for the rest.
        kinds = [unicodedata.category(c) for c in self.letters]
        self.kind = np.array([0 if k[0] == "L" else 1 if k == "Nd" else 2 for k in kinds], dtype=np.int64)[self.code] if self.n else np.zeros(0, np.int64)

    def embedding(self, dim: int) -> np.ndarray:
        """`features.hash_embedding` of texts that are in lower case: a row each."""
        k, row, places = len(self.letters), [], []

        def count(of: np.ndarray, words: list[bytes], which: np.ndarray) -> None:
            row.append(of)
            places.append(np.mod(xxhash64(words), 2 * dim)[which])

        at = np.flatnonzero(self.row[2:] == self.row[:-2]) if len(self.row) > 2 else np.zeros(0, np.int64)
        code = self.code.astype(np.int64)
        grams, which = _distinct((code[at] * k + code[at + 1]) * k + code[at + 2], k**3)
        count(self.row[at], ["".join(self.letters[i] for i in (g // k // k, g // k % k, g % k)).encode("utf-8", "surrogatepass") for g in grams.tolist()], which)
        empty = np.flatnonzero(self.size == 2)
        count(empty, [b"^$"], np.zeros(len(empty), np.int64))
        part = np.concatenate([[False], self.kind < 2, [False]])
        begin, end = np.flatnonzero(part[1:] & ~part[:-1]), np.flatnonzero(part[:-1] & ~part[1:])
        tokens = pa.array([self.joined[a:b] for a, b in zip(begin.tolist(), end.tolist(), strict=True)], pa.string()).dictionary_encode()
        count(self.row[begin], [t.encode("utf-8") for t in tokens.dictionary.to_pylist()], tokens.indices.to_numpy())
        counted = np.bincount(np.concatenate(row) * (2 * dim) + np.concatenate(places), minlength=self.n * 2 * dim).reshape(self.n, 2 * dim)
        raw = (counted[:, :dim] - counted[:, dim:]).astype(float)
        length = np.sqrt((raw * raw).sum(axis=1))[:, None]  # whole numbers: any order has the same sum
        return np.divide(raw, length, out=np.zeros_like(raw), where=length > 0)

    def format_bigrams(self) -> np.ndarray:
        """`features.format_ngrams` of pairs: a row a text."""
        inner = np.ones(len(self.row), bool)
        inner[np.cumsum(self.size) - 1] = inner[np.cumsum(self.size) - self.size] = False
        at = np.flatnonzero(inner[1:] & inner[:-1])
        return np.bincount(self.row[at] * 9 + self.kind[at] * 3 + self.kind[at + 1], minlength=self.n * 9).reshape(self.n, 9)


def _means(x: np.ndarray, starts: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Each candidate's mean of its cell."""
    return (np.add.reduceat(x, starts, axis=0) / np.bincount(of)[:, None])[of]


def _distance(x: np.ndarray, y: np.ndarray, kind: str) -> np.ndarray:
    dot = lambda a, b: sum((a[:, i] * b[:, i] for i in range(a.shape[1])), np.zeros(len(a)))
    if kind == "l1":
        return dot(np.abs(x - y), np.ones_like(x))
    if kind == "l2":
        return np.sqrt(dot(x - y, x - y))
    with np.errstate(invalid="ignore"):
        return 1 - dot(x, y) / np.sqrt(dot(x, x) * dot(y, y))


def names(models: tuple[str, ...], rules: list[str]) -> list[str]:
    """The features' names, in their order."""
    blocks = {"format": [f"format{i}" for i in range(9)], "embed": ["embed"], "vote": ["vote_share"], "rules": rules, "neighbour": ["neighbour"]}
    return [n for b, of in blocks.items() if b in models for n in of]


def static(models: tuple[str, ...], dim: int, kind: str, values: list[str], code: np.ndarray, starts: np.ndarray, of: np.ndarray, support: np.ndarray, texts: pa.Array, record: np.ndarray, cand: np.ndarray, rules: list[np.ndarray]) -> np.ndarray:
    """(feature, candidate).

    values: the batch's distinct values, code: each candidate's; starts, of: cells of candidates; texts: each
    record's values with blanks between; record, cand: of each claim; rules: numbers of each claim.
    """
    n, out = len(code), []
    if not n:
        return np.zeros((len(names(models, [f"rule{i}" for i in range(len(rules))])), 0))
    mean = lambda x: np.bincount(cand, x, n) / support
    if "format" in models:
        out += list(np.log1p(Texts(values).format_bigrams())[code].T)
    m = Texts([v.lower() for v in values]).embedding(dim)[code] if {"embed", "neighbour"} & set(models) else None
    if "embed" in models:
        out.append(_distance(m, _means(m, starts, of), kind))
    if "vote" in models:
        out.append(support / np.add.reduceat(support, starts)[of])
    if "rules" in models:
        out += [mean(x) for x in rules]
    if "neighbour" in models:
        found = texts.dictionary_encode()
        q = Texts([t.lower() for t in found.dictionary.to_pylist()]).embedding(dim)[found.indices.to_numpy()][record]
        j = np.concatenate([np.stack([mean(q[:, i]) for i in range(dim)], axis=1), m], axis=1)
        out.append(_distance(j, _means(j, starts, of), kind))
    return np.array(out).reshape(len(out), n)
