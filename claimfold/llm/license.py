"""Fuzzy search for short licence notices.

Texts are reduced to their words (ASCII letters in lower case, digits and all
characters beyond ASCII), joined by blanks.  A notice that may have k errors is
cut into k + 1 pieces; by the pigeonhole principle a place with at most k errors
holds one piece unchanged.  Exact search for the pieces gives candidate places,
and the regex library's bounded-error matching verifies each and tells its span
and its errors.  Words that tell one licence from another (names, versions,
clauses) must stand as they are; any other word may have few errors by its
length, and must not be a different word of CONFUSED.  The base phrases are
matched exactly, word by word.
"""

from __future__ import annotations

import bisect
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .words import Words, chunks

#: Base phrases and labels.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))

#: Notices in reduced form, and labels.  Words with a "!" must match exactly.
NOTICES = (
    ("licensed under the apache! license version 2! 0!", "apache-2.0"),
    ("licensed under the apache! license version 1! 1!", "apache-1.1"),
    ("released under the mit! license", "mit"),
    ("licensed under the mit! license", "mit"),
    ("permission is hereby granted free of charge to any person", "mit"),
    ("released under the bsd! license", "bsd"),
    ("licensed under the bsd! license", "bsd"),
    ("redistribution and use in source! and binary! forms", "bsd"),
    ("released under the isc! license", "isc"),
    ("licensed under the isc! license", "isc"),
    ("licensed under the gnu! general! public! license version 3!", "gpl-3.0"),
    ("licensed under the gnu! general! public! license version 2!", "gpl-2.0"),
    ("gnu! lesser! general! public! license", "lgpl"),
    ("gnu! affero! general! public! license", "agpl"),
    ("mozilla! public! license version 2! 0!", "mpl-2.0"),
    ("licensed under cc! by! nc! 4! 0!", "cc-by-nc"),
    ("licensed under cc! by! sa! 4! 0!", "cc-by-sa"),
    ("licensed under cc! by! nd! 4! 0!", "cc-by-nd"),
    ("licensed under cc! by! nc! sa! 4! 0!", "cc-by-nc-sa"),
    ("licensed under cc! by! nc! nd! 4! 0!", "cc-by-nc-nd"),
    ("creative commons! attribution 4! 0! international license", "cc-by"),
    ("creative commons! attribution noncommercial", "cc-by-nc"),
    ("creative commons! attribution sharealike", "cc-by-sa"),
    ("dedicated to the public! domain", "public-domain"),
    ("boost! software license version 1! 0!", "bsl-1.0"),
    ("eclipse! public! license version 2! 0!", "epl-2.0"),
    ("this program is free software you can redistribute it", "gpl"),
    ("all rights reserved", "reserved"),
)

#: Words that are a few letters away from a notice's but mean something else.
CONFUSED = frozenset("preserved deserved unreserved reversed observed lights nights fights sights unlicensed delicensed relicensed thunder wonder releases licensee licensor conversion aversion".split())

#: Bytes that separate words, once A-Z are lower-cased.
SEPARATORS = np.zeros(256, dtype=bool)
SEPARATORS[[*range(0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]] = True


@dataclass(frozen=True)
class Notice:
    words: str
    label: str
    errors: int
    seeds: tuple[tuple[int, bytes], ...]
    pattern: regex.Pattern


def word_errors(word: str) -> int:
    """Errors that a word may have: none if marked with "!" or short, one from four letters, two from seven and for "the"."""
    return 0 if word.endswith("!") else 2 if word == "the" or len(word) >= 7 else 1 if len(word) >= 4 else 0


def compile_notices(notices=NOTICES, per_error: int = 9, most: int = 4) -> list[Notice]:
    """One error is allowed for every `per_error` characters of a notice, `most` at most, and each word has its own bound."""
    out = []
    for marked, label in notices:
        loose = [(w.rstrip("!"), word_errors(w)) for w in marked.split()]
        words = " ".join(w for w, _ in loose)
        k = min(most, len(words) // per_error, sum(e for _, e in loose))
        cuts = [round(i * len(words) / (k + 1)) for i in range(k + 2)]
        seeds = tuple((a, words[a:b].encode()) for a, b in zip(cuts[:-1], cuts[1:], strict=True))
        parts = " ".join(f"((?:{regex.escape(w)}){{e<={min(e, k)}:[^ ]}})" if e else f"({regex.escape(w)})" for w, e in loose)
        out.append(Notice(words, label, k, seeds, regex.compile(rf"(?b)(?<=[ ]){parts}(?=[ ])")))
    return out


def reduce_words(w: Words) -> tuple[bytes, np.ndarray]:
    """Words of all texts as ' a b c ' in one byte string, and each word's place in it."""
    size = w.end - w.start
    place = np.cumsum(size + 1) - size
    out = np.full(int(place[-1] + size[-1] + 1) if len(size) else 1, 0x20, dtype=np.uint8)
    inside = np.repeat(place - w.start, size) + np.flatnonzero(_inside(w))
    out[inside] = w.bytes[_inside(w)]
    return out.tobytes(), place


def _inside(w: Words) -> np.ndarray:
    turn = np.zeros(len(w.bytes) + 1, dtype=np.int8)
    turn[w.start] += 1
    turn[w.end] -= 1
    return np.cumsum(turn)[:-1].astype(bool)


def find_notices(column: pa.Array, notices: list[Notice]) -> tuple[Words, list[tuple[int, int, int, str, int, int]]]:
    """The words, and (text, first word, last word, label, errors, notice length) of every verified place."""
    w = Words(column, lower=True, separators=SEPARATORS)
    data, place = reduce_words(w)
    first_place = np.append(place, len(data))[np.minimum(w.first, len(place))] if len(place) else np.zeros(w.n_docs + 1, np.int64)
    found = set()
    for notice in notices:
        meant = set(notice.words.split())
        tried = set()
        for offset, seed in notice.seeds:
            at = data.find(seed)
            while at >= 0:
                start = at - offset
                if start // 8 not in tried:
                    tried.add(start // 8)
                    word = max(0, int(np.searchsorted(place, at, side="right")) - 1)
                    doc = int(np.searchsorted(w.first, word, side="right")) - 1
                    lo = max(int(first_place[doc]) - 1, start - notice.errors - 9)
                    hi = min(int(place[w.first[doc + 1] - 1] + (w.end - w.start)[w.first[doc + 1] - 1] + 1), start + len(notice.words) + notice.errors + 9)
                    text = data[max(lo, 0) : hi].decode("utf-8", errors="surrogateescape")
                    m = notice.pattern.search(text)
                    if m and sum(m.fuzzy_counts) <= notice.errors and not any(g in CONFUSED and g not in meant for g in m.groups()):
                        a = max(lo, 0) + len(text[: m.start()].encode("utf-8", errors="surrogateescape"))
                        b = max(lo, 0) + len(text[: m.end()].encode("utf-8", errors="surrogateescape"))
                        i, j = int(np.searchsorted(place, a, side="right")) - 1, int(np.searchsorted(place, b - 1, side="right")) - 1
                        found.add((doc, max(i, int(w.first[doc])), j, notice.label, sum(m.fuzzy_counts), len(notice.words)))
                at = data.find(seed, at + 1)
    return w, best_places(found)


def best_places(found) -> list[tuple[int, int, int, str, int, int]]:
    """Of places that overlap, the one of the fewest errors; of those the longest, the first, the first by label.

    What is kept lies apart, so a sorted list of starts tells whether a place is free: n log n for n places.
    """
    starts: list[int] = []
    kept: dict[int, tuple] = {}
    for place in sorted(found, key=lambda f: (f[4], -f[5], f[1], f[3])):
        _, i, j, *_ = place
        at = bisect.bisect_right(starts, j)
        if at and kept[starts[at - 1]][2] >= i:
            continue
        bisect.insort(starts, i)
        kept[i] = place
    return [kept[i] for i in starts]


def base_places(w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, first word and phrase number of every place of a base phrase."""
    h = w.hashes()
    owner = w.owner()
    out = []
    for k, (phrase, _) in enumerate(BASE):
        want = Words(pa.array([phrase])).hashes()
        n = len(h) - len(want) + 1
        if n <= 0:
            continue
        ok = owner[:n] == owner[len(want) - 1 :]
        for i, x in enumerate(want):
            ok &= h[i : i + n] == x
        at = np.flatnonzero(ok)
        out.append((owner[at], at, np.full(len(at), k)))
    if not out:
        return (np.zeros(0, np.int64),) * 3
    return tuple(np.concatenate([o[i] for o in out]) for i in range(3))


SCHEMA = "n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<first:long,last:long,label:string,errors:int>>"


def scan(docs: DataFrame, id: str = "doc_id", text: str = "text", notices=NOTICES) -> DataFrame:
    """(id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans) for every row.

    score is 1 for an exact notice or base phrase, less the share of wrong
    characters for the best fuzzy one, 0 without any.  spans are word positions
    within the text, from 0; of places that overlap one is told (`best_places`).
    A null or empty text has no words, no labels and a score of 0; so has one that
    holds no notice, however long.  Repeated rows come back as often, each alike;
    an empty table gives no rows; other columns of docs are not read.
    """

    def run(batches):
        compiled = compile_notices(notices)
        for b in batches:
            rows = []
            for x, y in chunks(b.column(1)):
                w, found = find_notices(b.column(1).slice(x, y - x), compiled)
                doc, at, phrase = base_places(w)
                spans: dict[int, list] = {}
                for d, i, j, label, errors, size in found:
                    spans.setdefault(d, []).append((i - int(w.first[d]), j - int(w.first[d]), label, errors, size))
                hits: dict[int, list] = {}
                for d, i, k in zip(doc.tolist(), at.tolist(), phrase.tolist(), strict=True):
                    hits.setdefault(d, []).append((i - int(w.first[d]), BASE[k][1]))
                for d, n in enumerate(w.count.tolist()):
                    base, more = hits.get(d, []), spans.get(d, [])
                    own = {k for _, k in base}
                    score = max([0.0, *(1.0 for _ in base[:1]), *(1 - e / s for *_, e, s in more)])
                    places = [p for p, _ in base]
                    rows.append((n, len(base), min(places, default=None), max(places, default=None), ",".join(sorted(own)), ",".join(sorted(own | {m[2] for m in more})), score, [{"first": i, "last": j, "label": k, "errors": e} for i, j, k, e, _ in more]))
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 8
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.float64(), pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64()), ("label", pa.string()), ("errors", pa.int32())])))
            names = [c.split()[0] for c in SCHEMA.split(", ")]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True))], names=[id, *names])

    return docs.select(id, text).mapInArrow(run, f"`{id}` {docs.schema[id].dataType.simpleString()}, {SCHEMA}")
