"""The rivals of `baselines` over packed records: a pass a round for all of them, which returns sums by source and run.

What a rival keeps between rounds is a number a source and run; what it thinks of
candidates follows from these within the cell.  Rivals that see no seeds are the
same in every run and go through their rounds once.  A source states a value of a
cell once: an entity has a record a source, as replicas have.
"""

from __future__ import annotations

from collections.abc import Callable, Generator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.noise import mix
from ..plans.workspace import settle
from .baselines import _program, chi2inv
from .claims import CELL, RUN
from .packed import ARRAYS, CLAIMS, SCHEMA, UNKNOWN, Pack, Packed, Split, _packs, _part, rates

METHODS = ("majority_vote", "seed_accuracy_bayes", "iterative_bayes", "interval_weighted_vote", "claim_graph_propagation", "discriminative_source_model", "rewrite_then_vote")
Said = Callable[[Pack, int], np.ndarray]
#: What a rival asks of a round's pass: numbers of a batch's claims, the runs, and rows if not all; it is sent their sums.
Ask = tuple[Callable[["Claims", int], list[np.ndarray]], list[int], DataFrame | None]
Rounds = Generator[Ask, np.ndarray, Said]


class Claims:
    """A batch's claims as (candidate, source), and of each candidate how many its cell has."""

    def __init__(self, p: Pack, sources: np.ndarray):
        held = p.rec >= 0
        self.p, self.cand, self.n_sources = p, p.rec[held], len(sources)
        self.source = np.broadcast_to(np.searchsorted(sources, p.rec_source), p.rec.shape)[held]
        self.m = np.diff(np.append(p.starts, p.n))[p.of].astype(float)

    def scores(self, weight: np.ndarray) -> np.ndarray:
        """Sums of the claims' weights for each candidate."""
        return np.bincount(self.cand, weight, self.p.n)

    def by_source(self, x: np.ndarray, where: np.ndarray | None = None) -> np.ndarray:
        """Sums of claims' numbers for each source."""
        at = slice(None) if where is None else where
        return np.bincount(self.source[at], x[at], self.n_sources)

    def cells(self, x: np.ndarray) -> np.ndarray:
        return np.add.reduceat(x, self.p.starts)[self.p.of] if self.p.n else x

    def best(self, score: np.ndarray) -> np.ndarray:
        """Scores that differ by less than 1e-9 are ties; the least value has them."""
        return self.p.best(np.round(score, 9), np.arange(self.p.n))


def _truth_of(split: Split, seed: int) -> Callable[..., np.ndarray]:
    """The truth of each candidate's cell in a run, UNKNOWN where it isn't a seed's."""

    def truth(p: Pack, run: int, all_seeds: bool = False) -> np.ndarray:
        if all_seeds:
            return p.truth[p.cell]
        seeds = split.roles(p, run, seed)[0]
        return np.where(seeds[p.cell % max(p.n_entities, 1)], p.truth[p.cell], UNKNOWN)

    return truth


class Rivals:
    def __init__(self, packed: Packed, split: Split, runs: int, seed: int = 0):
        self.packed, self.split, self.runs, self.seed = packed, split, runs, seed
        self._truth = _truth_of(split, seed)
        found = packed.prepared.wide.select("source_id").where("source_id is not null").distinct().collect()  # a number a source, as models have
        self.sources = np.array(sorted(r["source_id"] for r in found), dtype=np.int64)
        self.size = self._sums(packed.rows, [(lambda c, r: [np.ones(len(c.cand))], [0])])[0][0, 0] if len(found) else np.zeros(0)

    def _sums(self, rows: DataFrame, asked: list[tuple[Callable[[Claims, int], list[np.ndarray]], list[int]]]) -> list[np.ndarray]:
        """Of each asked: sums by (run, i, source) of the i-th numbers that it has for a batch's claims; rows with a run are of that run."""
        n_attrs, sources, own = len(self.packed.attrs), self.sources, "run" in rows.columns

        def run(batches):
            sums: dict[tuple[int, int], np.ndarray] = {}
            for row, p in _packs(batches, n_attrs):
                c = Claims(p, sources)
                for k, (f, runs) in enumerate(asked):
                    for r in [row["run"]] if own else runs:
                        found = np.array([c.by_source(x) for x in f(c, r)]).ravel()
                        sums[k, r] = sums[k, r] + found if (k, r) in sums else found
            for (k, r), v in sums.items():
                yield pa.RecordBatch.from_pydict({"k": pa.array([k], pa.int32()), "run": pa.array([r], pa.int32()), "v": pa.array([v], pa.list_(pa.float64()))})

        parts = rows.select(*CLAIMS, *(["run"] if own else [])).mapInArrow(run, "k int, run int, v array<double>").select("k", "run", F.posexplode("v").alias("at", "v"))
        got = parts.groupBy("k", "run", "at").agg(F.sum("v").alias("v")).collect()
        out = []
        for k, (_, runs) in enumerate(asked):
            mine = [r for r in got if r["k"] == k]
            sums = np.zeros((max(runs) + 1, 1 + max((r["at"] for r in mine), default=-1)))
            for r in mine:
                sums[r["run"], r["at"]] = r["v"]
            out.append(sums.reshape(max(runs) + 1, -1, len(sources)))
        return out

    def _together(self, rivals: list[Rounds]) -> list[Said]:
        """What rivals say after their rounds: a pass serves a round of each."""
        said: dict[int, Said] = {}
        sent: dict[int, np.ndarray | None] = dict.fromkeys(range(len(rivals)))
        while sent:
            asked: dict[int, Ask] = {}
            for i, sums in sent.items():
                try:
                    asked[i] = rivals[i].send(sums)
                except StopIteration as e:
                    said[i] = e.value
            tables = {id(rows): rows for _, _, rows in asked.values()}
            of = {k: [i for i, a in asked.items() if id(a[2]) == k] for k in tables}
            sent = {}
            with ThreadPoolExecutor(max(len(tables), 1)) as pool:
                a_pass = inheritable_thread_target(self.packed.rows.sparkSession)(self._sums)
                for k, got in [(k, pool.submit(a_pass, self.packed.rows if rows is None else rows, [asked[i][:2] for i in of[k]])) for k, rows in tables.items()]:
                    sent |= dict(zip(of[k], got.result(), strict=True))
        return [said[i] for i in range(len(rivals))]

    # -- methods: each asks for sums, round by round, and returns what it says of a batch in a run --

    def majority_vote(self) -> Rounds:
        yield from ()
        return lambda p, r: p.first()

    def _labelled(self) -> Generator[Ask, np.ndarray, np.ndarray]:
        """(run, right and labelled, source) of claims on seeds."""
        truth = self._truth

        def known(c: Claims, r: int) -> list[np.ndarray]:
            t = truth(c.p, r)[c.cand]
            return [(t == c.cand).astype(float), (t != UNKNOWN).astype(float)]

        return (yield known, list(range(self.runs)), None)

    def seed_accuracy_bayes(self, smoothing: float = 1.0) -> Rounds:
        right, labelled = (yield from self._labelled()).transpose(1, 0, 2)
        pooled = right.sum() / labelled.sum() if labelled.sum() else 0.5
        a = np.clip(np.where(labelled > 0, (right + smoothing) / (labelled + 2 * smoothing), pooled), 0.01, 0.99)
        sources = self.sources

        def said(p: Pack, r: int) -> np.ndarray:
            c = Claims(p, sources)
            own = a[r][c.source]
            return c.best(c.scores(np.log(own) - np.log((1 - own) / np.maximum(c.m[c.cand] - 1, 1))))

        return said

    def iterative_bayes(self, a0: float = 0.8, max_iter: int = 20, eps: float = 1e-4) -> Rounds:
        accuracy, sources = np.full(len(self.sources), a0), self.sources

        def posterior(c: Claims, accuracy: np.ndarray) -> np.ndarray:
            a = np.clip(accuracy, 0.01, 0.99)[c.source]
            return c.p.softmax(c.scores(np.log(c.m[c.cand] * a / (1 - a))))

        for _ in range(max_iter):
            new = (yield lambda c, r, a=accuracy: [posterior(c, a)[c.cand]], [0], None)[0, 0] / np.maximum(self.size, 1)
            change, accuracy = np.abs(new - accuracy).max(initial=0), new
            if change < eps:
                break
        return lambda p, r: (c := Claims(p, sources)).best(posterior(c, accuracy))

    def interval_weighted_vote(self, alpha: float = 0.05, iters: int = 10) -> Rounds:
        q, sources = np.array([chi2inv(alpha / 2, n) for n in self.size]), self.sources
        weight = np.ones(len(sources))
        answer = lambda c, w: c.best(c.scores(w[c.source]))
        for _ in range(iters):
            lost = (yield lambda c, r, w=weight: [(answer(c, w)[c.p.cell[c.cand]] != c.cand).astype(float)], [0], None)[0, 0]
            weight = q / (lost + 1e-6)
        return lambda p, r: answer(Claims(p, sources), weight)

    def claim_graph_propagation(self, iters: int = 20, gain: float = 1.0, rival: float = 1.0) -> Rounds:
        means: list[np.ndarray] = []
        sources, truth = self.sources, self._truth

        def state(c: Claims, r: int) -> np.ndarray:
            """Scores of facts after the rounds whose sources' means are known."""
            t = truth(c.p, r)
            clamp, free = np.where(t == np.arange(c.p.n), 1.0, -1.0), t == UNKNOWN
            f = np.where(free, 0.0, clamp)
            for mean in means:
                up = np.maximum(f, 0.0)
                f = np.where(free, np.tanh(gain * c.scores(mean[r][c.source]) - rival * (c.cells(up) - up)), clamp)
            return f

        for _ in range(iters):
            sums = (yield lambda c, r: [state(c, r)[c.cand]], list(range(self.runs)), None)[:, 0]
            means.append(sums / np.maximum(self.size, 1))
        return lambda p, r: (c := Claims(p, sources)).best((state(c, r) + 1) / 2 + c.scores(np.ones(len(c.cand))) * 1e-6)

    def discriminative_source_model(self, mode: str = "auto", l2: float = 0.01, iters: int = 30, rate: float = 4.0) -> Rounds:
        runs, n_attrs, sources, truth_of = list(range(self.runs)), len(self.packed.attrs), self.sources, self._truth
        labelled = (yield from self._labelled())[:, 1]
        if mode == "auto":
            mode = "erm" if labelled.size and np.median(labelled[:, self.size > 0]) >= 10 else "em"
        rows, n = None, np.tile(self.size, (self.runs, 1))
        if mode == "erm":  # seeds alone teach
            split, seed = self.split, self.seed

            def seeds(batches):
                for _, p in _packs(batches, n_attrs):
                    for r in runs:
                        yield from _part(p, split.roles(p, r, seed)[0], r)

            rows, n = settle(self.packed.rows.select(*ARRAYS).mapInArrow(seeds, f"run int, {SCHEMA}"), "packed-seeds"), labelled
        w = np.ones((self.runs, len(sources)))
        softmax = lambda c, own: c.p.softmax(c.scores(own[c.source]))

        def gradient(c: Claims, r: int, w: np.ndarray) -> list[np.ndarray]:
            p, t = softmax(c, w[r]), truth_of(c.p, r, mode == "erm")
            soft = np.where(t != UNKNOWN, t == np.arange(c.p.n), p**2 if mode == "em" else 0.0)
            off = (soft / np.maximum(c.cells(soft), 1e-12) - p) * (1.0 if mode == "em" else t != UNKNOWN)
            return [off[c.cand]]

        for _ in range(iters):
            g = yield lambda c, r, w=w: gradient(c, r, w), runs, rows
            w = w + rate * ((g[:, 0] if g.size else 0.0) / np.maximum(n, 1) - 2 * l2 * w)
        return lambda p, r: (c := Claims(p, sources)).best(softmax(c, w[r]))

    # -- the rival that changes values -------------------------------------------------

    def rewrite_then_vote(self, truth: DataFrame, budget: int, votes: dict[int, tuple[int, int]]) -> dict[int, tuple[int, int]]:
        """(judged, right) by run.  truth: (entity_id, attr, value); votes: what the majority has, which cells keep where no value is rewritten."""
        cands = self.packed.cands
        first = cands.where("slot = 0").select(*CELL, F.col("value").alias("frequent"))
        found = cands.where("slot > 0").join(first, list(CELL)).groupBy("attr", F.col("value").alias("rare"), "frequent").agg(F.count(F.lit(1)).alias("n_entities"))
        found = settle(found.withColumn("program", _program("rare", "frequent")), "rewrite-pairs")
        last = [(r, *x) for r, x in enumerate(self.split.seeds) if x is not None]
        runs = F.broadcast(found.sparkSession.createDataFrame(last, "run int, _x long, _id long"))
        often = lambda df: df.crossJoin(runs)
        key = F.concat_ws("#", "attr", "run") if self.runs > 1 else F.col("attr")
        ranked = often(found.groupBy("attr", "program").agg(F.sum("n_entities").alias("n"))).orderBy(F.desc("n"), key, "program").limit(budget).select("attr", "program", "run")
        mine = (F.col("run").cast("long") * RUN + F.col("entity_id")).alias("_e")
        seed = F.struct(mix(f"(cast(run as bigint) * {RUN} + entity_id)", 0, 55, 1).alias("x"), mine.alias("id")) <= F.struct(F.col("_x").alias("x"), F.col("_id").alias("id"))
        oracle = settle(often(truth).where(seed).select("run", "attr", "value").distinct(), "rewrite-oracle")
        true, wrong = oracle.withColumnRenamed("value", "frequent").withColumn("ok", F.lit(1)), oracle.withColumnRenamed("value", "rare").withColumn("also", F.lit(1))
        seen = found.join(ranked, ["attr", "program"]).join(true, ["run", "attr", "frequent"], "left").join(wrong, ["run", "attr", "rare"], "left")
        share = F.avg((F.col("ok").isNotNull() & F.col("also").isNull()).cast("double"))
        accepted = seen.groupBy("run", "attr", "program").agg(share.alias("share")).where("share > 0.5").select("run", "attr", "program")
        rewrites = settle(found.join(accepted, ["attr", "program"]).groupBy("run", "attr", F.col("rare").alias("value")).agg(F.max_by("frequent", F.struct("n_entities", "frequent")).alias("to")), "rewrites")
        # Votes differ only in cells in which a value is rewritten.
        touched = cands.join(rewrites.select("run", "attr", "value"), ["attr", "value"]).select("run", *CELL).distinct().join(runs, "run").where(~seed).select("run", *CELL)
        rows = cands.join(touched, list(CELL)).join(rewrites, ["run", "attr", "value"], "left").groupBy("run", *CELL, F.coalesce("to", "value").alias("new"))
        rows = rows.agg(F.sum("support").alias("n"), F.max(F.when(F.col("slot") == 0, F.col("value"))).alias("_old"))
        cell = Window.partitionBy("run", *CELL)
        rows = rows.withColumn("_r", F.row_number().over(cell.orderBy(F.desc("n"), "new"))).withColumn("old", F.max("_old").over(cell)).where("_r = 1")
        right = lambda c: F.coalesce((F.col(c) == F.col("truth")).cast("long"), F.lit(0))
        gained = rows.join(truth.select(*CELL, F.col("value").alias("truth")), list(CELL)).groupBy("run").agg(F.sum(right("new") - right("old")).alias("gain")).collect()
        gain = {r["run"]: r["gain"] for r in gained}
        return {r: (n, right + gain.get(r, 0)) for r, (n, right) in votes.items()}

    def precisions(self, methods: tuple[str, ...], truth: DataFrame) -> dict[str, list[tuple[int, float]]]:
        """(run, precision) of each method; rounds of several go side by side."""
        if set(methods) - set(METHODS):
            raise ValueError(f"no such method: {sorted(set(methods) - set(METHODS))}")
        plain = [m for m in methods if m != "rewrite_then_vote"]
        plain += ["majority_vote"] if "majority_vote" not in plain and "rewrite_then_vote" in methods else []
        said = self._together([getattr(self, m)() for m in plain])
        counts = dict(zip(plain, self.packed.counts(lambda p, r: [f(p, r) for f in said], self.split, self.runs, self.seed, CLAIMS), strict=True)) if plain else {}
        if "rewrite_then_vote" in methods:
            counts["rewrite_then_vote"] = self.rewrite_then_vote(truth, 100 * self.runs, counts["majority_vote"])
        return {m: rates(counts[m]) for m in methods}
