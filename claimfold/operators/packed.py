"""Entities packed in batches of arrays, so that one pass over the records serves all runs and all fits of a workload.

The records and candidates of a batch of whole entities lie in one row, as binary
arrays of numbers.  What is static of them is the same in every run and fit, and
what depends on predictions depends on the entity's own alone.  So a stage is fitted on
all labelled and weakly labelled entities for all fits, runs and attributes together: in one
job, a task a model, where a task can hold what a model learns from, and by passes that sum
over the batches where it can't.  All entities are then answered in one pass through all
stages.  In one job sums go in the order in which `resolver.fit` has them: answers are equal.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.noise import mix, mix_numbers
from ..plans.workspace import partitions, release, settle
from . import packed_static, passes, resolver
from .claims import RUN, run_of
from .features import EXTRA

#: Records of a batch, about.
BATCH = 8_192
ARRAYS = {"entity": np.int64, "cell": np.int32, "slot": np.int32, "support": np.int64, "static": np.float64, "rec": np.int32, "rec_entity": np.int32, "rec_at": np.int32, "rec_source": np.int64, "truth": np.int32}
SCHEMA = ", ".join(f"{k} binary" for k in ARRAYS)
#: Those that tell who claims what, and where the truth is known.
CLAIMS = tuple(k for k in ARRAYS if k not in ("support", "static", "rec_at"))
UNCLAIMED, UNKNOWN = -1, -2


class Pack:
    """A batch: candidates by attribute, entity and value; a cell is attribute * entities + entity."""

    def __init__(self, arrays: dict[str, np.ndarray], n_attrs: int):
        self.__dict__ |= arrays
        self.arrays, self.n_attrs = arrays, n_attrs
        self.n, self.n_entities, self.n_records = len(self.cell), len(self.entity), len(self.rec_entity)
        self.rec = self.rec.reshape(n_attrs, self.n_records)
        self.static = self.static.reshape(-1, self.n) if self.n else np.zeros((0, 0))
        self.starts = np.flatnonzero(np.diff(self.cell, prepend=-1))
        self.held = self.cell[self.starts]  # the cells that have candidates
        self.of = np.repeat(np.arange(len(self.starts)), np.diff(np.append(self.starts, self.n)))
        self.ends = np.searchsorted(self.cell, np.arange(n_attrs + 1) * self.n_entities)

    @staticmethod
    def read(row: dict, n_attrs: int) -> Pack:
        return Pack({k: np.frombuffer(row[k], dtype) if k in row else np.zeros(0, dtype) for k, dtype in ARRAYS.items()}, n_attrs)

    def row(self) -> dict:
        return {k: np.ascontiguousarray(getattr(self, k), dtype).tobytes() for k, dtype in ARRAYS.items()}

    def take(self, chosen: np.ndarray) -> Pack:
        """The batch of some of the entities."""
        at = np.where(chosen, np.cumsum(chosen) - 1, -1)
        keep, few = chosen[self.cell % max(self.n_entities, 1)], int(chosen.sum())
        place = np.where(keep, np.cumsum(keep) - 1, -1)
        moved = lambda c: np.where(c >= 0, place[np.maximum(c, 0)] if self.n else c, c)
        records, cell = chosen[self.rec_entity], self.cell[keep]
        truth = self.truth.reshape(self.n_attrs, self.n_entities)[:, chosen]
        return Pack({
            "entity": self.entity[chosen], "cell": cell // max(self.n_entities, 1) * few + at[cell % max(self.n_entities, 1)], "slot": self.slot[keep], "support": self.support[keep], "static": self.static[:, keep].ravel(),
            "rec": moved(self.rec[:, records]).ravel(), "rec_entity": at[self.rec_entity[records]], "rec_at": self.rec_at[records], "rec_source": self.rec_source[records], "truth": moved(truth).ravel(),
        }, self.n_attrs)

    def first(self) -> np.ndarray:
        """The candidate of each cell that most claims back; -1 where there is none."""
        said = np.full(self.n_attrs * self.n_entities, -1)
        at = np.flatnonzero(self.slot == 0)
        said[self.cell[at]] = at
        return said

    def best(self, score: np.ndarray, order: np.ndarray) -> np.ndarray:
        """The candidate of each cell of the highest score, of those the first in `order`."""
        said = np.full(self.n_attrs * self.n_entities, -1)
        if self.n:
            top = score == np.maximum.reduceat(score, self.starts)[self.of]
            order = np.where(top, order.astype(np.int64), np.int64(1 << 40))
            at = np.flatnonzero(top & (order == np.minimum.reduceat(order, self.starts)[self.of]))
            said[self.cell[at]] = at
        return said

    def softmax(self, z: np.ndarray) -> np.ndarray:
        e = np.exp(z - np.maximum.reduceat(z, self.starts)[self.of]) if self.n else z
        return self.share(e)

    def share(self, e: np.ndarray) -> np.ndarray:
        return e / np.add.reduceat(e, self.starts)[self.of] if self.n else e

    def judged(self, said: np.ndarray, test: np.ndarray) -> tuple[int, int]:
        """(answered cells of known truth, right ones) of the entities of a mask."""
        counts = np.tile(test, self.n_attrs) & (said >= 0) & (self.truth != UNKNOWN)
        return int(counts.sum()), int((counts & (said == self.truth)).sum())


def _packs(batches: Iterator[pa.RecordBatch], n_attrs: int) -> Iterator[tuple[dict, Pack]]:
    for batch in batches:
        for i in range(batch.num_rows):
            row = {k: batch.column(k)[i].as_buffer() if k in ARRAYS else batch.column(k)[i].as_py() for k in batch.schema.names}
            yield row, Pack.read(row, n_attrs)


def _part(p: Pack, chosen: np.ndarray, run: int) -> Iterator[pa.RecordBatch]:
    """A run's part of a batch as a row, where it has entities."""
    if chosen.any():
        yield pa.RecordBatch.from_pydict({"run": pa.array([run], pa.int32()), **{k: pa.array([v], pa.binary()) for k, v in p.take(chosen).row().items()}})


def _packer(attrs: tuple[str, ...], s: resolver.Settings, used: list[str], of: dict[str, list[str]]):
    """Records with counts of rules (and rows of truth) of a bucket of entities to one row of arrays and its candidates' values."""

    def run(table: pa.Table) -> pa.Table:
        entity = table["entity_id"].to_numpy()
        own = np.unique(entity)
        n_e, where = len(own), np.searchsorted(own, entity)
        flat = lambda c: pa.concat_arrays([x.cast(pa.string()) for x in c.chunks]) if c.num_chunks else pa.array([], pa.string())
        said = [flat(table[a]) for a in attrs]
        every = pa.concat_arrays(said).dictionary_encode()
        words, order = len(every.dictionary), pc.array_sort_indices(every.dictionary)
        rank = np.empty(max(words, 1), dtype=np.int64)
        rank[order.to_numpy()] = np.arange(words)
        codes = np.where(every.is_valid().to_numpy(zero_copy_only=False), rank[every.indices.fill_null(0).to_numpy()], -1).reshape(len(attrs), -1)
        cells = np.arange(len(attrs))[:, None] * n_e + where
        true, at = table["truth"].to_numpy(zero_copy_only=False).astype(bool), table["at"].fill_null(-1).to_numpy()
        records = np.flatnonzero(~true)
        records = records[np.lexsort((at[records], where[records]))]
        claimed = codes[:, records] >= 0
        keys, cand, support = np.unique((cells[:, records] * max(words, 1) + codes[:, records])[claimed], return_inverse=True, return_counts=True)
        n, cell, code = len(keys), keys // max(words, 1), keys % max(words, 1)
        starts = np.flatnonzero(np.diff(cell, prepend=-1))
        group = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, n)))
        slot = np.empty(n, np.int64)
        slot[np.lexsort((code, -support, cell))] = np.arange(n) - starts[group]
        rec = np.full(claimed.shape, -1)
        rec[claimed] = cand
        truth = np.full((len(attrs), n_e), UNKNOWN)
        if n:  # the candidate that has the true value
            wanted = cells[:, true] * max(words, 1) + codes[:, true]
            found = np.minimum(np.searchsorted(keys, wanted), n - 1)
            truth[:, where[true]] = np.where(codes[:, true] < 0, UNKNOWN, np.where(keys[found] == wanted, found, UNCLAIMED))
        else:
            truth[:, where[true]] = np.where(codes[:, true] < 0, UNKNOWN, UNCLAIMED)
        attr, record = np.nonzero(claimed)
        rules = [np.where(np.array([r in of[a] for a in attrs])[attr], np.log1p(table[r].to_numpy().astype(float))[records][record], 0.0) for r in used]
        # The join shortens a row of nulls alone by a blank that it hasn't: each row begins with an empty text.
        texts = pc.utf8_slice_codeunits(pc.binary_join_element_wise(pa.scalar(""), *said, pa.scalar(" "), null_handling="skip"), 1).take(pa.array(records))
        values = every.dictionary.take(order)
        static = packed_static.static(s.models, s.embed_dim, s.dist, values.to_pylist(), code, starts, group, support, texts, record, cand, rules)
        pack = Pack({
            "entity": own, "cell": cell, "slot": slot, "support": support, "static": static.ravel(),
            "rec": rec.ravel(), "rec_entity": where[records], "rec_at": at[records], "rec_source": table["source_id"].fill_null(-1).to_numpy()[records], "truth": truth.ravel(),
        }, len(attrs))
        mine = values.take(pa.array(code))
        return pa.table({**{k: pa.array([v], pa.binary()) for k, v in pack.row().items()}, "value": pa.ListArray.from_arrays(pa.array([0, n], pa.int32()), mine)})

    return run


@dataclass(frozen=True)
class Split:
    """The last of the seeds of each run, and of the known and other entities that models learn from, by noise and id."""

    seeds: tuple
    known: tuple
    weak: tuple

    @staticmethod
    def _below(noise: np.ndarray, ids: np.ndarray, last: tuple | None) -> np.ndarray:
        return np.zeros(len(ids), bool) if last is None else (noise < last[0]) | ((noise == last[0]) & (ids <= last[1]))

    def roles(self, p: Pack, run: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(seed, known, validation, weak) of a batch's entities in a run."""
        ids = p.entity + run * RUN
        true = (p.truth.reshape(p.n_attrs, -1) != UNKNOWN).any(axis=0)
        claimed = np.zeros(p.n_entities, bool)
        claimed[p.held % max(p.n_entities, 1)] = True
        seeds = true & self._below(mix_numbers(ids, 0, 55, 1), ids, self.seeds[run])
        known = seeds & self._below(mix_numbers(ids, 3, 91, seed), ids, self.known[run])
        weak = ~seeds & claimed & self._below(mix_numbers(ids, 5, 91, seed), ids, self.weak[run])
        return seeds, known, known & (mix_numbers(ids, 0, 55, seed + 11) % 10000 >= 8000), weak


class Packed:
    """Packed records of a workload with what is static of them; answers and precisions of fits and rivals, for all runs at once."""

    def __init__(self, wide: DataFrame, s: resolver.Settings, truth: DataFrame):
        """wide: records of one run; s: its blocks are those that fits may have; truth: (entity_id, attributes), a row an entity."""
        plain = {"layout": "candidate", "embed": "hash", "slot_order": "support", "rule_partners": "raw", "augment": 0.0}
        if any(getattr(s, k) != v for k, v in plain.items()) or set(s.models) & set(EXTRA):
            raise ValueError("packed records have the layout 'candidate', hashed embeddings and rules over records")
        s = replace(s, runs=1)
        wide = resolver.number_records(wide, s, "packed-records")
        self.attrs, self.sources = tuple(s.attrs), resolver.source_list(wide, s)
        rows, used, of = resolver._rule_counts(wide, s)
        self.names = packed_static.names(s.models, used)
        self.prepared = resolver.Prepared(s, wide, None, self.names, self.sources)
        buckets = max(1, round(wide.count() / BATCH))
        b = F.pmod(F.xxhash64("entity_id"), F.lit(buckets)).alias("_b")
        kept = [F.col(a).cast("string").alias(a) for a in self.attrs]
        records = resolver.indexed(rows, self.sources).select(b, "entity_id", F.col("source_id").cast("long").alias("source_id"), "at", F.lit(False).alias("truth"), *kept, *used)
        records = records.union(truth.select(b, "entity_id", F.lit(None).cast("long"), F.lit(None).cast("int"), F.lit(True), *kept, *[F.lit(0).cast("long")] * len(used)))
        # Batches are dealt over all partitions, which few bytes wouldn't keep apart by themselves.
        self.rows = settle(records.repartition(partitions(wide), "_b").groupBy("_b").applyInArrow(_packer(self.attrs, s, used, of), f"{SCHEMA}, value array<string>"), "packed")

    @property
    def cands(self) -> DataFrame:
        """(entity_id, attr, value, support, slot): a row a candidate."""
        attrs = self.attrs

        def run(batches):
            for batch in batches:
                for i in range(batch.num_rows):
                    get = lambda k, b=batch, i=i: np.frombuffer(b.column(k)[i].as_buffer(), ARRAYS[k])
                    entity, cell = get("entity"), get("cell")
                    names = pa.DictionaryArray.from_arrays(pa.array(cell // max(len(entity), 1), pa.int32()), pa.array(attrs, pa.string())).cast(pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(entity[cell % max(len(entity), 1)]), names, batch.column("value")[i].values, pa.array(get("support")), pa.array(get("slot"))], ["entity_id", "attr", "value", "support", "slot"])

        return self.rows.select("entity", "cell", "support", "slot", "value").mapInArrow(run, "entity_id long, attr string, value string, support long, slot int")

    def split(self, share: float, runs: int, s: resolver.Settings) -> Split:
        """The share's entities of least noise are the seeds of a run, one at least; models learn from these and all others, or from `max_train` of each."""
        n_attrs = len(self.attrs)

        def run(batches):
            for _, p in _packs(batches, n_attrs):
                claimed = np.zeros(p.n_entities, bool)
                claimed[p.held % max(p.n_entities, 1)] = True
                yield pa.RecordBatch.from_pydict({"id": pa.array(p.entity), "known": pa.array((p.truth.reshape(n_attrs, -1) != UNKNOWN).any(axis=0)), "claimed": pa.array(claimed)})

        rows = self.rows.select(*CLAIMS).mapInArrow(run, "id long, known boolean, claimed boolean")
        rows = rows.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))).withColumn("id", F.col("run").cast("long") * RUN + F.col("id"))
        at = F.struct(mix("id", 0, 55, 1).alias("x"), "id")
        by = Window.partitionBy("run", "known")
        rows = rows.withColumn("_r", F.row_number().over(by.orderBy(at))).withColumn("_n", F.count(F.lit(1)).over(by))
        rows = rows.withColumn("seed", F.col("known") & (F.col("_r") <= F.greatest(F.lit(1), F.round(F.col("_n") * share)))).where("seed or claimed or known")
        to = F.struct(F.when(F.col("seed"), mix("id", 3, 91, s.seed)).otherwise(mix("id", 5, 91, s.seed)).alias("x"), "id")
        able = F.col("seed") | F.col("claimed")
        few = F.lit(True) if s.max_train is None else F.row_number().over(Window.partitionBy("run", "seed", "able").orderBy(to)) <= s.max_train
        rows = rows.withColumn("able", able).withColumn("_t", few)
        last = {r["run"]: r for r in rows.groupBy("run").agg(F.max(F.when(F.col("seed"), at)).alias("seeds"), F.max(F.when(F.col("seed") & F.col("_t"), to)).alias("known"), F.max(F.when(~F.col("seed") & F.col("able") & F.col("_t"), to)).alias("weak")).collect()}
        get = lambda k: tuple(tuple(last[r][k]) if r in last and last[r][k] is not None else None for r in range(runs))
        return Split(get("seeds"), get("known"), get("weak"))

    def _columns(self, s: resolver.Settings) -> list[int]:
        return self.prepared.columns(s)

    def fit(self, fits: list[resolver.Settings], split: Split, runs: int) -> list[resolver.Fitted]:
        """What resolver.fit has of each, without history."""
        n_attrs, attrs, sources = len(self.attrs), self.attrs, self.sources
        plain = {"rule_partners": "raw", "early_stop": None, "dynamic_from": "model", "first_dynamic": "vote", "trust": False, "pick": "argmax", "cooc_values": "predicted"}
        if not all(self.prepared.shares(s) and all(getattr(s, k) == v for k, v in plain.items()) for s in fits) or len({(s.seed, s.max_train, s.stages) for s in fits}) > 1:
            raise ValueError("fits of the layout 'candidate' that share records, stages and sample are needed, without other dynamic features")
        seed = fits[0].seed

        taught = self.rows.select(*ARRAYS)
        if fits[0].max_train is not None:

            def sample(batches):
                for _, p in _packs(batches, n_attrs):
                    for r in range(runs):
                        _, known, _, weak = split.roles(p, r, seed)
                        yield from _part(p, known | weak, r)

            taught = settle(taught.mapInArrow(sample, f"run int, {SCHEMA}"), "packed-sample")
        plans = [Plan(s, self._columns(s), attrs, len(sources) + 1 if sources and s.use_source and "source" in s.models else 0) for s in fits]
        out = [resolver.Fitted(s, list(sources) if p.n_sources else [], [*[self.names[i] for i in p.columns], *p.dynamic], []) for s, p in zip(fits, plans, strict=True)]
        width = max(len(p.columns) + len(p.dynamic) + p.n_sources for p in plans)
        stage_of = self._by_passes if self._most(taught) * width > passes.TASK_NUMBERS else self._by_tasks
        said = None
        for stage in range(fits[0].stages):
            models = [resolver.StageModel(stage, 0.0) for _ in fits]
            made, said = stage_of(plans, taught, said, split, runs, stage)
            for k, got in sorted(made.items()):  # one model an attribute, run and fit
                i, key = k.split("|", 1)
                m = models[int(i)]
                m.weights[key], m.means[key], m.scales[key] = got["w"], got["mean"], got["scale"]
                m.platt[key], m.l2 = (got["a"], got["b"]), got["l2"]
            for p, m, f in zip(plans, models, out, strict=True):
                p.models.append(m)
                f.stages.append(m)
        if said is not None:
            release(said)
        return out

    def _most(self, taught: DataFrame) -> int:
        """The candidates of the attribute (in the run) that has the most."""
        n_attrs = len(self.attrs)

        def run(batches):
            for row, p in _packs(batches, n_attrs):
                yield pa.RecordBatch.from_pydict({"run": pa.array([row.get("run", 0)] * n_attrs, pa.int32()), "a": pa.array(range(n_attrs), pa.int32()), "n": pa.array(np.diff(p.ends), pa.int64())})

        counted = taught.select("entity", "cell", "rec_entity", "rec", *(["run"] if "run" in taught.columns else [])).mapInArrow(run, "run int, a int, n long")
        return counted.groupBy("run", "a").agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0

    def _by_tasks(self, plans: list[Plan], taught: DataFrame, said: DataFrame | None, split: Split, runs: int, stage: int) -> tuple[dict[str, dict], DataFrame | None]:
        """Models of a stage in one job, a task a model."""
        rows = taught.mapInArrow(_lessons(plans, split, runs, stage), "key string, n int, x binary, entity binary, slot binary, y binary, part binary, weight binary, place binary, at binary")
        made = rows.repartition(4 * partitions(rows), "key").groupBy("key").applyInArrow(_learn(plans), "key string, model string").collect()
        return {r["key"]: json.loads(r["model"]) for r in made}, None

    def _by_passes(self, plans: list[Plan], taught: DataFrame, said: DataFrame | None, split: Split, runs: int, stage: int) -> tuple[dict[str, dict], DataFrame | None]:
        """Models of a stage by passes over the batches; beside these lies what the stages before say, which the next stage goes on from."""
        rows = taught
        if stage:
            own = ["run"] if "run" in taught.columns else []
            source = taught if said is None else said
            rows = settle(source.mapInArrow(_saying(plans, runs, stage), ", ".join([*[f"{k} int" for k in own], SCHEMA, "said binary"])), "packed-said")
            if said is not None:
                release(said)

        def passed(work, keys, valid):
            return passes.total(rows, _taught(plans, split, runs, stage, keys, valid), work)

        def start(key: str, d: int) -> np.ndarray:
            """The last stage's weights, of features as they are."""
            i, k = key.split("|", 1)
            m = plans[int(i)].models[-1] if stage else None
            if m is None or k not in m.weights:
                return np.zeros(d)
            w = np.array(m.weights[k])
            w[: len(m.scales[k])] /= m.scales[k]
            return w

        return passes.fit(passed, lambda key: plans[int(key.split("|", 1)[0])].s, start), rows if stage else None

    def counts(self, answers: Callable[[Pack, int], list[np.ndarray]], split: Split, runs: int, seed: int = 0, need: tuple[str, ...] = tuple(ARRAYS)) -> list[dict[int, tuple[int, int]]]:
        """Of each list of answers (a candidate a cell) that a batch and run get: (judged, right) by run, over the entities that aren't seeds."""
        n_attrs = len(self.attrs)

        def run(batches):
            for _, p in _packs(batches, n_attrs):
                for r in range(runs):
                    test = ~split.roles(p, r, seed)[0]
                    found = [p.judged(said, test) for said in answers(p, r)]
                    yield pa.RecordBatch.from_pydict({"i": pa.array(range(len(found)), pa.int32()), "run": pa.array([r] * len(found), pa.int32()), "n": pa.array([f[0] for f in found], pa.int64()), "right": pa.array([f[1] for f in found], pa.int64())})

        rows = self.rows.select(*need).mapInArrow(run, "i int, run int, n long, right long").groupBy("i", "run").agg(F.sum("n").alias("n"), F.sum("right").alias("right")).collect()
        out: list[dict[int, tuple[int, int]]] = [{} for _ in range(1 + max((r["i"] for r in rows), default=-1))]
        for r in rows:
            out[r["i"]][r["run"]] = (r["n"], r["right"])
        return out

    def precisions(self, answers: Callable[[Pack, int], list[np.ndarray]], split: Split, runs: int, seed: int = 0) -> list[list[tuple[int, float]]]:
        """(run, precision) of each list of answers."""
        return [rates(found) for found in self.counts(answers, split, runs, seed)]

    def resolve(self, fits: list[resolver.Settings], split: Split, runs: int) -> list[list[tuple[int, float]]]:
        """(run, precision) of each fit: models of all labelled and weakly labelled entities, then one pass over all."""
        plans = [Plan(f.settings, self._columns(f.settings), self.attrs, len(f.sources) + 1 if f.sources else 0, f.stages) for f in self.fit(fits, split, runs)]
        return self.precisions(lambda p, r: [plan.forward(p, r) for plan in plans], split, runs, fits[0].seed)


def rates(counts: dict[int, tuple[int, int]]) -> list[tuple[int, float]]:
    return sorted((r, right / n) for r, (n, right) in counts.items() if n)


class Plan:
    """A fit over packs: its static columns, its models so far, and the way through its stages."""

    def __init__(self, s: resolver.Settings, columns: list[int], attrs: tuple[str, ...], n_sources: int, models: list[resolver.StageModel] | None = None):
        self.s, self.columns, self.attrs, self.n_sources, self.models = s, columns, attrs, n_sources, models or []
        self.cooc, self.running = "cooc" in s.models and len(attrs) > 1, "running" in s.models
        self.dynamic = [*([f"cooc_{a}" for a in attrs] if self.cooc else []), *(["running"] if self.running else [])]

    def key(self, a: int, run: int) -> str:
        return self.attrs[a] if self.s.runs == 1 else f"{self.attrs[a]}#{run}"

    def features(self, p: Pack, said: np.ndarray, stage: int) -> list[np.ndarray]:
        """A column a feature, in the order of the resolver's."""
        out = [p.static[i] for i in self.columns]
        if self.cooc:
            agree = [((p.rec[b] >= 0) & (p.rec[b] == said[b * p.n_entities + p.rec_entity])).astype(float) for b in range(p.n_attrs)]
            for b in range(p.n_attrs):
                total = np.bincount(p.rec_entity, agree[b], p.n_entities)[p.cell % max(p.n_entities, 1)]
                ratio = np.zeros(p.n)
                for a in range(p.n_attrs):
                    lo, hi = p.ends[a], p.ends[a + 1]
                    if a != b and hi > lo:
                        ok = p.rec[a] >= 0
                        pairs, of = np.bincount(p.rec[a][ok] - lo, agree[b][ok], hi - lo), total[lo:hi]
                        ratio[lo:hi] = np.divide(pairs, of, out=np.zeros(hi - lo), where=of > 0)
                out.append(ratio)
        if self.running:
            out.append((np.arange(p.n) == said[p.cell]).astype(float) if stage else np.zeros(p.n))
        return out

    def probabilities(self, p: Pack, x: list[np.ndarray], m: resolver.StageModel, run: int) -> np.ndarray:
        z = np.zeros(p.n)
        moved = not all(tuple(ab) == (1.0, 0.0) for ab in m.platt.values())
        slope, shift = np.ones(p.n), np.zeros(p.n)
        for a in range(p.n_attrs):
            k, lo, hi = self.key(a, run), p.ends[a], p.ends[a + 1]
            if k not in m.weights or hi == lo:
                continue
            w, n = m.weights[k], len(m.means[k])
            scaled = np.array(w[:n]) / np.array(m.scales[k])
            part = np.zeros(hi - lo)
            for column, v in zip(x, scaled.tolist(), strict=True):  # one after another, as Spark adds them
                part += column[lo:hi] * v
            part -= float(scaled @ np.array(m.means[k]))
            if self.n_sources:
                odds = np.array([*w[n:], 0.0])
                ok = (p.rec[a] >= 0) & (p.rec_at >= 0)
                part += np.bincount(p.rec[a][ok] - lo, odds[np.minimum(p.rec_at[ok], len(odds) - 1)], hi - lo)
            z[lo:hi], (slope[lo:hi], shift[lo:hi]) = part, m.platt[k]
        q = p.softmax(z)
        if not moved:
            return q
        c = np.clip(q, 1e-9, 1 - 1e-9)
        with np.errstate(over="ignore"):
            c = np.where(q > 0, 1 / (1 + np.exp(-(slope * np.log(c / (1 - c)) + shift))), 0.0)
        total = np.add.reduceat(c, p.starts)[p.of] if p.n else c
        return np.divide(c, total, out=q.copy(), where=total > 0)

    def forward(self, p: Pack, run: int, until: int | None = None) -> np.ndarray:
        """The answers after the stages that have models (or the first of them)."""
        said = p.first()
        for stage, m in enumerate(self.models[:until]):
            said = p.best(self.probabilities(p, self.features(p, said, stage), m, run), p.slot)
        return said


def _each(p: Pack, run: int, plan: Plan, said: np.ndarray, stage: int, roles: tuple, wanted: Callable[[int], bool] = lambda a: True):
    """(attribute, places of candidates, vectors, truths, parts, claims' candidates and sources) of what a batch teaches the models of a fit."""
    _, known, validation, weak = roles
    e = p.cell % max(p.n_entities, 1)
    x = plan.features(p, said, stage)
    label = np.where(np.tile(known, p.n_attrs), p.truth, said)[p.cell]
    use = known[e] & (p.truth[p.cell] != UNKNOWN)
    if plan.s.train_on != "seed" and plan.s.weak_weight > 0:
        use |= weak[e]
    part = np.where(weak[e], passes.WEAK, np.where(validation[e], passes.VALIDATION, passes.TRAIN)).astype(np.int8)
    for a in range(p.n_attrs):
        at = p.ends[a] + np.flatnonzero(use[p.ends[a] : p.ends[a + 1]])
        if not len(at) or not wanted(a):
            continue
        place, source = np.zeros(0, np.int32), np.zeros(0, np.int32)
        if plan.n_sources:
            to = np.full(p.n, -1)
            to[at] = np.arange(len(at))
            ok = (p.rec[a] >= 0) & (p.rec_at >= 0)
            ok[ok] = to[p.rec[a][ok]] >= 0
            place, source = to[p.rec[a][ok]].astype(np.int32), p.rec_at[ok]
        vectors = np.stack([c[at] for c in x], axis=1) if x else np.zeros((len(at), 0))
        yield a, at, vectors, (label[at] == at).astype(np.float64), part[at], place, source


def _runs(row: dict, runs: int) -> list[int]:
    """The runs of a batch: a sample's own, or all."""
    return [row["run"]] if "run" in row else list(range(runs))


def _lessons(plans: list[Plan], split: Split, runs: int, stage: int):
    """What each model of a stage learns from: vectors of the candidates of labelled cells."""

    def run(batches):
        for row, p in _packs(batches, len(plans[0].attrs)):
            e = p.cell % max(p.n_entities, 1)
            for r in _runs(row, runs):
                roles = split.roles(p, r, plans[0].s.seed)
                for i, plan in enumerate(plans):
                    for a, at, x, y, part, place, source in _each(p, r, plan, plan.forward(p, r, stage), stage, roles):
                        weight = np.where(part == passes.WEAK, plan.s.weak_weight, 1.0)
                        cells = {"x": x, "entity": p.entity[e[at]] + r * RUN, "slot": p.slot[at].astype(np.int32), "y": y, "part": part, "weight": weight, "place": place, "at": source.astype(np.int32)}
                        yield pa.RecordBatch.from_pydict({"key": pa.array([f"{i}|{plan.key(a, r)}"]), "n": pa.array([len(at)], pa.int32()), **{k: pa.array([v.tobytes()], pa.binary()) for k, v in cells.items()}})

    return run


def _before(row: dict, p: Pack, plans: list[Plan], runs: int) -> Callable[[int, int], np.ndarray] | None:
    """What the stages before say of a batch, by run and fit, where it lies beside it."""
    if "said" not in row:
        return None
    said = np.frombuffer(row["said"], np.int32).reshape(len(_runs(row, runs)), len(plans), -1)
    return lambda r, i: said[_runs(row, runs).index(r), i]


def _saying(plans: list[Plan], runs: int, stage: int):
    """Batches with what each fit says after the models that there are, in each run."""

    def run(batches):
        for row, p in _packs(batches, len(plans[0].attrs)):
            before, out = _before(row, p, plans, runs), []
            for r in _runs(row, runs):
                for i, plan in enumerate(plans):
                    said = p.first() if before is None else before(r, i)
                    out.append(p.best(plan.probabilities(p, plan.features(p, said, stage - 1), plan.models[-1], r), p.slot).astype(np.int32))
            yield pa.RecordBatch.from_pydict({**({"run": pa.array([row["run"]], pa.int32())} if "run" in row else {}), **{k: pa.array([row[k].to_pybytes()], pa.binary()) for k in ARRAYS}, "said": pa.array([np.array(out).tobytes()], pa.binary())})

    return run


def _taught(plans: list[Plan], split: Split, runs: int, stage: int, keys: set[str] | None, valid: bool):
    """(model, lesson) of the batches, for the models of some keys or all; of validation cells alone if so told."""

    def run(batches):
        for row, p in _packs(batches, len(plans[0].attrs)):
            before = _before(row, p, plans, runs)
            for r in _runs(row, runs):
                roles = split.roles(p, r, plans[0].s.seed)
                part = p.take(roles[2]) if valid else p
                for i, plan in enumerate(plans):
                    wanted = lambda a, i=i, plan=plan, r=r: keys is None or f"{i}|{plan.key(a, r)}" in keys
                    if not part.n or not any(map(wanted, range(p.n_attrs))):
                        continue
                    said = plan.forward(part, r, stage) if valid or before is None else before(r, i)
                    for a, at, x, y, role, place, source in _each(part, r, plan, said, stage, tuple(v[roles[2]] for v in roles) if valid else roles, wanted):
                        ok = source < plan.n_sources
                        block = np.bincount(place[ok].astype(np.int64) * plan.n_sources + source[ok], minlength=len(at) * plan.n_sources).reshape(len(at), plan.n_sources)
                        yield f"{i}|{plan.key(a, r)}", passes.Lesson(np.hstack([x, block]), y, part.cell[at], role, x.shape[1])

    return run


_KINDS = {"x": np.float64, "entity": np.int64, "slot": np.int32, "y": np.float64, "part": np.int8, "weight": np.float64, "place": np.int32, "at": np.int32}


def _learn(plans: list[Plan]):
    def run(key: tuple, table: pa.Table) -> pa.Table:
        name = key[0].as_py()
        plan = plans[int(name.split("|", 1)[0])]
        rows = [{k: np.frombuffer(r[k], d) for k, d in _KINDS.items()} | {"n": r["n"]} for r in table.to_pylist()]
        begin = np.cumsum([0, *[r["n"] for r in rows]])
        get = lambda k: np.concatenate([r[k] for r in rows])
        n = int(begin[-1])
        block = np.zeros((n, plan.n_sources))
        for r, lo in zip(rows, begin, strict=False):
            ok = r["at"] < plan.n_sources
            np.add.at(block, (r["place"][ok] + lo, r["at"][ok]), 1)
        entity, slot = get("entity"), get("slot")
        order = np.lexsort((slot, entity))
        parts = np.array(["train", "validation", "weak"])[get("part")]  # by passes.TRAIN, VALIDATION, WEAK
        got = resolver.candidate_fit(get("x").reshape(n, -1)[order], block[order], get("y")[order], entity[order], parts[order], get("weight")[order], plan.s)
        return pa.table({"key": [name], "model": [json.dumps(got)]})

    return run
