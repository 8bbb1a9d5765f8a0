"""Quality rules: every rule is evaluated once and kept as bits and measurements.

`measure` makes one pass over the texts, `ledger` turns measurements into a
bitmask of failed rules, `apply_policy` decides with a versioned mask, and
`ablation` counts what each rule or pair of rules decides, by bitwise
aggregation over the stored masks alone: no text is read again.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import fresh
from .words import Words, chunks, rolling, window_owner

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")

#: Rules in the order of their bits.  A rule is a condition under which a text fails.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", "n_words < 50"),
    ("repeated_trigrams", "100 * n_repeat_words > 50 * n_words"),
    ("symbols", "10 * n_symbols > n_words"),
    ("duplicate_lines", "2 * n_dup_lines > n_lines"),
    ("long_words", "word_chars > 15 * n_words"),
    ("no_words", "n_words = 0"),
    ("many_words", "n_words > 1000000"),
)


@dataclass(frozen=True)
class Policy:
    """A named, versioned choice of rules that reject."""

    name: str
    version: int
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        names = [n for n, _ in RULES]
        return sum(1 << names.index(r) for r in self.rules)


#: The base rules alone, and the default of the pipeline.
BASE = Policy("base", 1, ("few_words", "repeated_trigrams"))
DEFAULT = Policy("default", 1, ("few_words", "repeated_trigrams", "symbols", "duplicate_lines", "long_words"))

_SYMBOL = np.zeros(256, dtype=np.int64)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = 1


def _per_doc(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sums of values between consecutive starts."""
    sums = np.zeros(len(values) + 1, dtype=np.int64)
    np.cumsum(values, out=sums[1:])
    return sums[starts[1:]] - sums[starts[:-1]]


def _repeats(keys: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each entry, whether its (owner, key) came before, and whether it comes twice or more."""
    order = np.lexsort((keys, owner))
    k, o = keys[order], owner[order]
    same = np.zeros(len(k) + 1, dtype=bool)
    same[1:-1] = (k[1:] == k[:-1]) & (o[1:] == o[:-1])
    before, twice = np.zeros(len(k), dtype=bool), np.zeros(len(k), dtype=bool)
    before[order] = same[:-1]  # lexsort is stable: the first of a run is the earliest
    twice[order] = same[:-1] | same[1:]
    return before, twice


def measure_column(column: pa.Array) -> dict[str, np.ndarray]:
    """The measurements of each text; null counts as empty, and an empty text has zeros."""
    out: dict[str, list[np.ndarray]] = {m: [np.zeros(0, np.int64)] for m in MEASURES}
    for a, b in chunks(column):
        w = Words(column.slice(a, b - a))
        inside = np.zeros(len(w.bytes) + 1, dtype=np.int64)
        np.add.at(inside, w.start, 1)
        np.add.at(inside, w.end, -1)
        inside = np.cumsum(inside)[:-1].astype(bool)
        out["n_words"].append(w.count.astype(np.int64))
        out["word_chars"].append(_per_doc((inside & ((w.bytes & 0xC0) != 0x80)).astype(np.int64), w.doc_start))
        out["n_symbols"].append(_per_doc(_SYMBOL[w.bytes], w.doc_start))
        # Lines: cut at each line feed and at each text's end.
        cut = w.bytes == 0x0A
        cut[w.doc_start[1:] - 1] = True
        end = np.flatnonzero(cut)
        start = np.concatenate([[0], end[:-1] + 1])
        worded = np.searchsorted(w.start, end) > np.searchsorted(w.start, start)
        start, end = start[worded], end[worded]
        owner = np.searchsorted(w.doc_start, start, side="right") - 1
        out["n_lines"].append(np.bincount(owner, minlength=w.n_docs).astype(np.int64))
        before, _ = _repeats(w.span_hashes(start, end), owner)
        out["n_dup_lines"].append(np.bincount(owner[before], minlength=w.n_docs).astype(np.int64))
        # Words covered by a window of three that its text holds twice or more.
        first, owner = window_owner(w, 3)
        _, twice = _repeats(rolling(w.hashes(), 3)[first], owner)
        covered = np.zeros(len(w.start) + 3, dtype=bool)
        for i in range(3):
            covered[first[twice] + i] = True
        out["n_repeat_words"].append(_per_doc(covered[: len(w.start)].astype(np.int64), w.first))
    return {m: np.concatenate(v) for m, v in out.items()}


def measure(docs: DataFrame, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, measurements) for every row, in one narrow pass; repeated rows stay repeated."""
    kind = docs.schema[id].dataType.simpleString()

    def run(batches):
        for b in batches:
            got = measure_column(b.column(1))
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(got[m]) for m in MEASURES)], names=[id, *MEASURES])

    return docs.select(id, text).mapInArrow(run, f"`{id}` {kind}, " + ", ".join(f"{m} long" for m in MEASURES))


def failure_bits(names: dict[str, str] | None = None) -> Column:
    """The bitmask of failed rules, from measurement columns, which may have other names."""
    names = names or {m: m for m in MEASURES}
    bits = F.lit(0).cast("long")
    for k, (_, fails) in enumerate(RULES):
        fails = re.sub(rf"\b({'|'.join(MEASURES)})\b", lambda m: f"`{names[m[1]]}`", fails)
        bits = bits.bitwiseOR(F.when(F.expr(fails), F.lit(1 << k)).otherwise(F.lit(0)).cast("long"))
    return bits


def ledger(docs: DataFrame, id: str = "doc_id", text: str = "text") -> DataFrame:
    """Measurements and `failed`, the bitmask of all rules that the text fails."""
    return measure(docs, id, text).withColumn("failed", failure_bits())


def apply_policy(book: DataFrame, policy: Policy = DEFAULT) -> DataFrame:
    """`kept`: no rule of the policy failed; `policy` names the version applied."""
    return book.withColumn("kept", F.col("failed").bitwiseAND(F.lit(policy.mask)) == 0).withColumn("policy", F.lit(f"{policy.name}@{policy.version}"))


def ablation(book: DataFrame, policy: Policy = DEFAULT) -> DataFrame:
    """For each rule of the policy: texts that fail it, fail it alone, and stay rejected without it."""
    names = [n for n, _ in RULES]
    masked = book.select(F.col("failed").bitwiseAND(F.lit(policy.mask)).alias("f"))
    tally = masked.groupBy("f").count()
    rules = [(n, 1 << names.index(n)) for n in policy.rules]
    aggs = [F.struct(F.lit(n).alias("rule"), F.coalesce(F.sum(F.when(F.col("f").bitwiseAND(F.lit(bit)) != 0, F.col("count"))), F.lit(0)).alias("failed"), F.coalesce(F.sum(F.when(F.col("f") == bit, F.col("count"))), F.lit(0)).alias("failed_alone"), F.coalesce(F.sum(F.when(F.col("f").bitwiseAND(F.lit(policy.mask & ~bit)) != 0, F.col("count"))), F.lit(0)).alias("rejected_without")) for n, bit in rules]
    return tally.agg(F.array(*aggs).alias("rows")).select(F.explode("rows").alias("r")).select("r.*")


def screen(docs: DataFrame, text: str = "text", policy: Policy = DEFAULT) -> DataFrame:
    """The rows of docs that the policy keeps, all columns as they are; no shuffle.

    A null text counts as empty, and has few words.  Repeated rows are judged
    each alone, texts of any length whole; an empty table gives no rows.
    """
    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields]
    at, bits = docs.columns.index(text), fresh(docs, "failed")
    measures = {m: fresh(docs, f"_q_{m}") for m in MEASURES}

    def run(batches):
        for b in batches:
            got = measure_column(b.column(at))
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(got[m]) for m in MEASURES)], names=[*b.schema.names, *measures.values()])

    measured = docs.mapInArrow(run, ", ".join([*fields, *(f"`{c}` long" for c in measures.values())]))
    judged = measured.withColumn(bits, failure_bits(measures))
    return judged.where(F.col(bits).bitwiseAND(F.lit(policy.mask)) == 0).select(*[F.col(f"`{c}`") for c in docs.columns])
