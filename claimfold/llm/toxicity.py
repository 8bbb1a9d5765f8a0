"""Toxicity by a lexicon that tolerates misspelling, with the context of each hit.

The lexicon is learnt from labelled rows: words, and stems that several words
share, which toxic texts have and others do not.  Its trie is intersected with
Levenshtein automata of one edit (for terms of five characters or more) into one
deterministic table, so a batch's words run through it side by side, a character
at a time.  A hit is exact, by stem, or misspelled; a misspelled hit counts only
where its spelling is no word of the clean training texts.  A window around each
hit tells quotation (quote marks on both sides) from use.  A logistic model over
counts of hits gives the score.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import thin
from .words import chunks

#: Labelled rows that are learnt from, at most: those of the smallest hashes.
SAMPLE_ROWS = 20_000
FUZZY_LENGTH, STEM_LENGTH, WINDOW = 5, 4, 40
QUOTES = "\"'“”„«»‘’‹›`"
FEATURES = ("any", "exact", "stem", "misspelled", "quoted", "strength")

_word_char: np.ndarray | None = None


def word_chars() -> np.ndarray:
    """Which code points make words: letters, marks of letters and digits, as Python's isalnum has them."""
    global _word_char
    if _word_char is None:
        _word_char = np.fromiter((chr(i).isalnum() for i in range(0x110000)), dtype=bool, count=0x110000)
    return _word_char


@dataclass
class Lexicon:
    """Terms, stems and the table of their automaton."""

    terms: list[str]
    stems: list[str]
    excluded: frozenset[str] = frozenset()
    #: Log-odds of a term or stem in toxic against clean training texts.
    strength: dict[str, float] = field(default_factory=dict)
    table: np.ndarray = field(default=None, repr=False)
    accept: np.ndarray = field(default=None, repr=False)
    classes: np.ndarray = field(default=None, repr=False)

    def __post_init__(self):
        entries = [(t, False) for t in self.terms] + [(s, True) for s in self.stems]
        letters = {c: i + 1 for i, c in enumerate(sorted({c for t, _ in entries for c in t}))}
        children: list[dict[str, int]] = [{}]
        final: list[int] = [-1]  # 0 term, 1 stem
        fuzzy: list[bool] = [False]  # whether a term of enough length ends below
        for t, is_stem in entries:
            node, path = 0, [0]
            for c in t:
                if c not in children[node]:
                    children[node][c] = len(children)
                    children.append({})
                    final.append(-1)
                    fuzzy.append(False)
                node = children[node][c]
                path.append(node)
            final[node] = 1 if is_stem else max(final[node], 0)
            if not is_stem and len(t) >= FUZZY_LENGTH:
                for n in path:
                    fuzzy[n] = True
        long_end = {n for t, is_stem in entries if not is_stem and len(t) >= FUZZY_LENGTH for n in [self._walk(children, t)]}

        def closure(states: set[tuple[int, int]]) -> frozenset:
            out = set(states)
            for node, e in states:
                if e == 0:  # a character of the term left out
                    out |= {(n, 1) for n in children[node].values() if fuzzy[n]}
            return frozenset(out)

        def step(states: frozenset, c: str) -> frozenset:
            out = set()
            for node, e in states:
                if node < 0:
                    out.add((node, e))  # below a stem anything goes
                    continue
                n = children[node].get(c)
                if n is not None and (e == 0 or fuzzy[n]):
                    out.add((n, e))
                    if e == 0 and final[n] == 1:
                        out.add((-1, 0))
                if e == 0 and fuzzy[node]:
                    out.add((node, 1))  # a character too many
                    out |= {(m, 1) for m in children[node].values() if fuzzy[m]}  # a wrong one
            return closure(out)

        start = closure({(0, 0)})
        number, queue, rows = {frozenset(): 0, start: 1}, [start], [[0] * (len(letters) + 1)]
        for states in queue:
            row = []
            for c in ["", *letters]:
                after = step(states, c)
                if after not in number:
                    number[after] = len(number)
                    queue.append(after)
                row.append(number[after])
            rows.append(row)
        self.table = np.array(rows, dtype=np.int32)
        # 0 none, 1 exact, 2 stem, 3 misspelled
        self.accept = np.zeros(len(number), dtype=np.int8)
        for states, i in number.items():
            if any(e == 0 and n >= 0 and final[n] == 0 for n, e in states):
                self.accept[i] = 1
            elif any(n == -1 or (n >= 0 and e == 0 and final[n] == 1) for n, e in states):
                self.accept[i] = 2
            elif any(n in long_end for n, e in states):
                self.accept[i] = 3
        self.classes = np.zeros(0x110000, dtype=np.uint8 if len(letters) < 255 else np.uint16)
        for c, i in letters.items():
            self.classes[ord(c)] = i

    @staticmethod
    def _walk(children: list[dict[str, int]], term: str) -> int:
        node = 0
        for c in term:
            node = children[node][c]
        return node

    def match(self, points: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The kind of hit of each word, all words side by side."""
        kind = np.zeros(len(start), dtype=np.int8)
        who, state, at = np.arange(len(start)), np.ones(len(start), dtype=np.int32), start.copy()
        classes = self.classes[points]
        while len(who):
            state = self.table[state, classes[at]]
            at = at + 1
            live = state > 0
            who, state, at = who[live], state[live], at[live]
            done = at == end[who]
            kind[who[done]] = self.accept[state[done]]
            who, state, at = who[~done], state[~done], at[~done]
        return kind


def spans(texts: list[str | None]) -> tuple[str, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The lower-cased texts in one string with a line feed between, code points, word spans, owners."""
    lowered = [(t or "").lower() for t in texts]
    joined = "\n".join(lowered) + "\n"
    points = np.frombuffer(joined.encode("utf-32-le", errors="surrogatepass"), dtype=np.uint32)
    inside = np.zeros(len(points) + 1, dtype=bool)
    inside[1:] = word_chars()[points]
    turn = np.flatnonzero(inside[1:] != inside[:-1])
    ends = np.cumsum([len(t) + 1 for t in lowered])
    return joined, points, turn[0::2], turn[1::2], np.searchsorted(ends, turn[0::2], side="right")


def hits(texts: list[str | None], lexicon: Lexicon) -> list[tuple[int, str, int, bool]]:
    """(text, spelling, kind, quoted) of every hit."""
    joined, points, start, end, owner = spans(texts)
    if not len(start):
        return []
    kind = lexicon.match(points, start, end)
    out = []
    for i in np.flatnonzero(kind).tolist():
        a, b = int(start[i]), int(end[i])
        word = joined[a:b]
        if kind[i] == 3 and word in lexicon.excluded:
            continue
        before, after = joined[max(0, a - WINDOW) : a], joined[b : b + WINDOW]
        before, after = before[before.rfind("\n") + 1 :], after.split("\n", 1)[0]
        quoted = any(q in before for q in QUOTES if q != "'") and any(q in after for q in QUOTES if q != "'")
        out.append((int(owner[i]), word, int(kind[i]), quoted))
    return out


def features(texts: list[str | None], lexicon: Lexicon) -> np.ndarray:
    """FEATURES of each text: whether it has a hit, logarithms of one more than the counts of distinct spellings, and the
    greatest strength of a term or stem used; a misspelled one counts as the weakest of all."""
    seen: list[list[set]] = [[set(), set(), set(), set()] for _ in texts]
    strong, weakest = [0.0] * len(texts), min(lexicon.strength.values(), default=0.0)
    for doc, word, kind, quoted in hits(texts, lexicon):
        seen[doc][3 if quoted else kind - 1].add(word)
        if not quoted:
            known = [word] if kind == 1 else [word[:k] for k in range(STEM_LENGTH, len(word) + 1)] if kind == 2 else []
            strong[doc] = max([strong[doc], weakest if kind == 3 else 0.0, *(lexicon.strength.get(x, 0.0) for x in known)])
    x = np.zeros((len(texts), len(FEATURES)))
    for i, sets in enumerate(seen):
        n = [math.log2(1 + len(s)) for s in sets]
        x[i] = [float(any(n[:3])), *n, strong[i]]
    return x


@dataclass
class Model:
    lexicon: Lexicon
    weights: np.ndarray

    def score(self, texts: list[str | None]) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.weights[0] + features(texts, self.lexicon) @ self.weights[1:])))


def _fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 30) -> np.ndarray:
    """Newton's method with a ridge on all but the constant."""
    x = np.hstack([np.ones((len(x), 1)), x])
    w = np.zeros(x.shape[1])
    penalty = np.diag([1e-6, *[ridge] * (x.shape[1] - 1)])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + penalty @ w
        h = (x * (p * (1 - p))[:, None]).T @ x + penalty
        step = np.linalg.solve(h, g)
        w -= np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    return w


def _word_tallies(batches):
    """For each word and stem: the clean documents that have it, and its contexts in toxic ones.

    A context is the hash of the words on both sides; copies of a document repeat
    their contexts, so they don't make a rare word look like common abuse.
    """
    for b in batches:
        clean: dict[tuple[str, bool], int] = {}
        toxic: set[tuple[str, bool, int, int]] = set()
        label = b.column("toxic").to_pylist()
        for x, y in chunks(b.column("text")):
            texts = b.column("text").slice(x, y - x).to_pylist()
            joined, _, start, end, owner = spans(texts)
            prints = [zlib.crc32(t.encode()) for t in texts]
            words = [joined[s:e] for s, e in zip(start.tolist(), end.tolist(), strict=True)]
            once, owners = set(), owner.tolist()
            for i, (o, word) in enumerate(zip(owners, words, strict=True)):
                if label[x + o]:
                    before = words[i - 1] if i and owners[i - 1] == o else ""
                    after = words[i + 1] if i + 1 < len(words) and owners[i + 1] == o else ""
                    around = zlib.crc32(f"{before} {after}".encode(errors="replace"))
                    toxic.add((word, False, around, prints[o]))
                    toxic |= {(word[:k], True, around, prints[o]) for k in range(STEM_LENGTH, min(len(word), STEM_LENGTH + 5))}
                else:
                    once.add((o, word))
            for _, word in once:
                clean[word, False] = clean.get((word, False), 0) + 1
            for _, stem in {(o, w[:k]) for o, w in once for k in range(STEM_LENGTH, min(len(w), STEM_LENGTH + 5))}:
                clean[stem, True] = clean.get((stem, True), 0) + 1
        rows = [(w, k, n, None, None) for (w, k), n in clean.items()] + [(w, k, 0, c, d) for w, k, c, d in toxic]
        columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
        yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, (pa.string(), pa.bool_(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["word", "stem", "clean", "context", "print"])


def choose_terms(rows: list[tuple[str, bool, int, int]]) -> tuple[list[str], list[str]]:
    """Terms and stems by toxic documents; a stem must cover words that are no term alone, and no longer stem of it stays."""
    terms = [w for w, stem, *_ in rows if not stem]
    stems: list[str] = []
    held = set(terms)
    for s in sorted((w for w, stem, *_ in rows if stem), key=lambda w: (len(w), w)):
        below = sum(1 for t in held if t.startswith(s))
        if below >= 3 and not any(s.startswith(x) for x in stems):
            stems.append(s)
    return terms, stems


def fit(docs: DataFrame, labels: DataFrame, train: Column, id: str = "doc_id", text: str = "text", label: str = "toxic", sample_rows: int = SAMPLE_ROWS) -> Model | None:
    """Learn from at most `sample_rows` labelled rows for which `train` holds; None without both labels.

    A term needs as many different toxic texts, and contexts in them, as 1 % of
    these, three at least, and 20 times the share that clean texts have of it; so
    the sample bounds the lexicon.  Of labels that repeat an id, 1 wins; of
    documents that do, the text that sorts first.  Ids and labels that are null,
    and other labels, teach nothing; a null text counts as empty.
    """
    known = labels.select(F.col(id).alias("id"), F.col(label).cast("int").alias("toxic")).where("id is not null and toxic in (0, 1)")
    known = known.groupBy("id").agg(F.max("toxic").alias("toxic"))
    known = known.where(train).withColumn("h", F.xxhash64("id"))
    known = thin(known, "h", known.count(), sample_rows).orderBy("h", "id").limit(sample_rows).drop("h")
    sample = docs.select(F.col(id).alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(F.broadcast(known), "id")
    sample = sample.groupBy("id").agg(F.min("text").alias("text"), F.first("toxic").alias("toxic")).persist()
    try:
        size = {r["toxic"]: r["count"] for r in sample.groupBy("toxic").count().collect()}
        n, t = size.get(0, 0), size.get(1, 0)
        if not n or not t:
            return None
        least = max(3, -(-t // 100))
        tallies = sample.select("text", "toxic").mapInArrow(_word_tallies, "word string, stem boolean, clean long, context long, print long").groupBy("word", "stem").agg(F.sum("clean").alias("clean"), F.least(F.count_distinct("context"), F.count_distinct("print")).alias("toxic"))
        ratio = ((F.col("toxic") + 0.5) / (t + 1)) / ((F.col("clean") + 0.5) / (n + 1))
        chosen = tallies.where((F.col("toxic") >= least) & (ratio >= 20) & (F.length("word") >= 3)).orderBy("word", "stem")
        rows = [tuple(r) for r in chosen.select("word", "stem", "clean", "toxic").collect()]
        terms, stems = choose_terms(rows)
        lexicon = Lexicon(terms, stems)
        odds = {(w, stem): math.log((toxic + 0.5) / (t + 1)) - math.log((clean + 0.5) / (n + 1)) for w, stem, clean, toxic in rows}
        lexicon.strength = {s: odds[s, True] for s in stems} | {w: odds[w, False] for w in terms}

        def misspelled(batches):
            for b in batches:
                found = {w for x, y in chunks(b.column("text")) for _, w, k, _ in hits(b.column("text").slice(x, y - x).to_pylist(), lexicon) if k == 3}
                yield pa.RecordBatch.from_arrays([pa.array(sorted(found), pa.string())], names=["word"])

        clean = sample.where("toxic = 0").select("text").mapInArrow(misspelled, "word string").distinct()
        lexicon.excluded = frozenset(r["word"] for r in clean.collect())

        def measured(batches):
            for b in batches:
                x = np.concatenate([np.zeros((0, len(FEATURES))), *(features(b.column("text").slice(s, e - s).to_pylist(), lexicon) for s, e in chunks(b.column("text")))])
                yield pa.RecordBatch.from_arrays([b.column("toxic"), *(pa.array(x[:, j]) for j in range(len(FEATURES)))], names=["toxic", *FEATURES])

        rows = sample.select("text", "toxic").mapInArrow(measured, "toxic int, " + ", ".join(f"`{f}` double" for f in FEATURES))
        rows = rows.groupBy("toxic", *FEATURES).count().toArrow()
        x = np.stack([rows.column(f).to_numpy() for f in FEATURES], axis=1)
        times = rows.column("count").to_numpy()
        order = np.lexsort(x.T)
        x, times, y = x[order], times[order], rows.column("toxic").to_numpy()[order]
        return Model(lexicon, _fit_logistic(np.repeat(x, times, axis=0), np.repeat(y, times).astype(float)))
    finally:
        sample.unpersist()


def score_documents(docs: DataFrame, model: Model | None, id: str = "doc_id", text: str = "text", threshold: float = 0.3) -> DataFrame:
    """(id, score, predicted) for every row; without a model every score is 0.

    A null text counts as empty; texts without a hit, empty ones too, have one
    score.  Rows are scored each alone and whole, so repeated rows come back as
    often and alike; an empty table gives no rows; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for b in batches:
            parts = [m.score(b.column(1).slice(x, y - x).to_pylist()) if m else np.zeros(y - x) for x, y in chunks(b.column(1))]
            score = np.concatenate([np.zeros(0), *parts])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=[id, "score", "predicted"])

    return docs.select(id, text).mapInArrow(run, f"`{id}` {docs.schema[id].dataType.simpleString()}, score double, predicted int")
