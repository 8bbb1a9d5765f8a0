"""Models of the layout 'candidate' by sums over all that they learn from, for all models of a stage at once.

A pass over the lessons returns, of each model, the losses and gradients at the weights
that its ridges try next; the driver keeps these few numbers and no lesson leaves
its batch.  What is minimised, and chosen, is what `resolver.candidate_fit` has: means and scales
of all lessons, each ridge on the training cells, the best on validation cells, calibration on
these, and a last fit on both.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from ..plans.workspace import partitions
from .learn import platt_step, platt_sums

#: Numbers (candidates times features) that a model may learn from in one task; beyond, passes sum over batches.
TASK_NUMBERS = 4_000_000
#: Features up to which the curvature at the start is a matrix; beyond it is a number a feature.
DENSE = 512
#: Steps after which a search ends, near or not; convex ones are near after some 20.
ROUNDS = 100
TRAIN, VALIDATION, WEAK = 0, 1, 2
TEMPERATURES = (0.5, 0.7, 0.85, 1.0, 1.2, 1.5, 2.0)


class Lesson:
    """What a batch teaches a model: candidates by cell with vectors (features, then claims by source), labels and parts."""

    def __init__(self, x: np.ndarray, y: np.ndarray, cell: np.ndarray, part: np.ndarray, n_features: int):
        self.x, self.y, self.cell, self.part, self.n_features = x, y, cell, part, n_features
        self.starts = np.flatnonzero(np.diff(cell, prepend=-1))
        self.size = np.diff(np.append(self.starts, len(cell)))
        self.of = np.repeat(np.arange(len(self.starts)), self.size)
        self.has = np.add.reduceat(y, self.starts) > 0 if len(y) else np.zeros(0, bool)
        self.role = part[self.starts]

    def cells(self, chosen: np.ndarray) -> Lesson:
        keep = chosen[self.of]
        return Lesson(self.x[keep], self.y[keep], self.cell[keep], self.part[keep], self.n_features)

    def shares(self, z: np.ndarray) -> np.ndarray:
        """Softmax within cells, a column a set of weights."""
        e = np.exp(z - np.maximum.reduceat(z, self.starts, axis=0)[self.of])
        return e / np.add.reduceat(e, self.starts, axis=0)[self.of]

    def curvature(self, w: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Second derivatives of the loss at raw weights; their diagonal where features are many."""
        d = self.x.shape[1]
        if not len(self.y):
            return np.zeros(d * d if d <= DENSE else d)
        p = self.shares((self.x @ w)[:, None])
        off = self.x - np.add.reduceat(self.x * p, self.starts, axis=0)[self.of]
        p *= weight[self.of, None]
        return ((off * p).T @ off).ravel() if d <= DENSE else (off * off * p).sum(axis=0)

    def slopes(self, w: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Of each column of raw weights the loss and its gradient, one after another; weight: a number a cell."""
        if not len(self.y):
            return np.zeros((1 + self.x.shape[1]) * w.shape[1])
        p = self.shares(self.x @ w)
        loss = -weight @ np.log(np.maximum(p[self.y > 0], 1e-12))
        p -= self.y[:, None]
        p *= weight[self.of, None]
        return np.vstack([loss, self.x.T @ p]).ravel()

    def losses(self, w: np.ndarray) -> np.ndarray:
        return -np.log(np.maximum(self.shares(self.x @ w)[self.y > 0], 1e-12)).sum(axis=0) if len(self.y) else np.zeros(w.shape[1])

    def logits(self, w: np.ndarray) -> np.ndarray:
        p = self.shares((self.x @ w)[:, None])[:, 0] if len(self.y) else np.zeros(0)
        return np.log(np.clip(p, 1e-9, 1 - 1e-9) / np.clip(1 - p, 1e-9, 1))


#: A pass's work on a lesson: named sums of a model's; names that begin with "moments" are merged as means and squares.
Work = Callable[[str, Lesson], Iterator[tuple[str, np.ndarray]]]


def _merged(name: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    if not name.startswith("moments"):
        return a + b
    d, n = len(a) // 2, a[0] + b[0]
    if not a[0] or not b[0]:
        return a if a[0] else b
    off = b[1 : d + 1] - a[1 : d + 1]
    return np.concatenate([[n], a[1 : d + 1] + off * (b[0] / n), a[d + 1 :] + b[d + 1 :] + off * off * (a[0] * b[0] / n)])


def total(rows: DataFrame, lessons: Callable[[Iterator[pa.RecordBatch]], Iterator[tuple[str, Lesson]]], work: Work) -> dict[tuple[str, str], np.ndarray]:
    """Sums by (model, name) of a pass; partial ones are added in the order of partitions."""

    def run(batches):
        sums: dict[tuple[str, str], np.ndarray] = {}
        for key, lesson in lessons(batches):
            for name, v in work(key, lesson):
                sums[key, name] = _merged(name, sums[key, name], v) if (key, name) in sums else v
        at = TaskContext.get().partitionId()
        for (key, name), v in sums.items():
            yield pa.RecordBatch.from_pydict({"key": [key], "name": [name], "part": pa.array([at], pa.int32()), "v": pa.array([np.asarray(v, float).tobytes()], pa.binary())})

    def add(key: tuple, table: pa.Table) -> pa.Table:
        out = None
        for r in table.sort_by("part").to_pylist():
            v = np.frombuffer(r["v"])
            out = v if out is None else _merged(r["name"], out, v)
        return pa.table({"key": [key[0].as_py()], "name": [key[1].as_py()], "v": pa.array([out.tobytes()], pa.binary())})

    parts = rows.mapInArrow(run, "key string, name string, part int, v binary")
    got = parts.repartition(partitions(rows), "key").groupBy("key", "name").applyInArrow(add, "key string, name string, v binary").collect()  # a few numbers a model
    return {(r["key"], r["name"]): np.frombuffer(r["v"]) for r in got}


class Search:
    """The least of a convex function whose value and slope are told pass by pass.

    Newton's steps where the curvature is told too, quasi-Newton ones from a first curvature where it isn't.
    """

    def __init__(self, w: np.ndarray, near: float, inverse: np.ndarray | None = None):
        self.trial, self.inverse, self.near = w, inverse, near
        self.w: np.ndarray | None = None
        self.seen: list[tuple[np.ndarray, np.ndarray, float]] = []
        self.done, self.told = False, 0

    def _metric(self, g: np.ndarray) -> np.ndarray:
        q, alphas = g.copy(), []
        for s, y, r in reversed(self.seen):
            alphas.append(r * (s @ q))
            q -= alphas[-1] * y
        q = self.inverse @ q if self.inverse.ndim == 2 else self.inverse * q
        for (s, y, r), a in zip(self.seen, reversed(alphas), strict=True):
            q += (a - r * (y @ q)) * s
        return q

    def tell(self, f: float, g: np.ndarray, inverse: np.ndarray | None = None) -> None:
        self.told += 1
        if self.w is not None:
            if f > self.f - 1e-4 * self.t * self.slope + 1e-14:
                if self.t < 1e-6:  # rounding alone is left
                    self.done = True
                    return
                self.t *= min(0.5, max(0.1, self.slope * self.t / (2 * (f - self.f + self.slope * self.t))))
                self.trial = self.w - self.t * self.step
                return
            s, y = self.trial - self.w, g - self.g
            if inverse is None and s @ y > 0:
                self.seen = [*self.seen[-29:], (s, y, 1 / (s @ y))]
        if inverse is not None:
            self.inverse = inverse
        self.w, self.f, self.g = self.trial, f, g
        self.step, self.t = self._metric(g), 1.0
        self.slope = g @ self.step
        self.trial = self.w - self.step
        if self.slope < self.near or self.told >= ROUNDS:  # nearer than the loss can tell: the whole step
            self.w, self.done = self.trial, True


class _Platt:
    """Newton's steps for (a, b) of sigmoid(a * logit + b), as learn.platt_fit has its loss."""

    def __init__(self):
        self.at, self.trial, self.t, self.done, self.told = None, np.array([1.0, 0.0]), 1.0, False, 0

    def tell(self, n: float, v: np.ndarray) -> None:
        self.told += 1
        f, g, h = platt_step(v, n, *self.trial)
        if self.at is not None and f > self.f + 1e-15 and self.t > 1e-6 and self.told < ROUNDS:
            self.t /= 2
            self.trial = self.at - self.t * self.step
            return
        self.at, self.f, self.t, self.step = self.trial, f, 1.0, np.linalg.solve(h, g)
        self.trial = self.at - self.step
        if g @ self.step < 1e-14 or self.told >= ROUNDS:
            self.at, self.done = self.trial, True


class _Model:
    """What the driver knows of a model between passes; weights are of scaled features."""

    def __init__(self, s, n_features: int, start: np.ndarray, sums: dict[str, np.ndarray]):
        m, (self.n_train, self.n_weak, all_weak, self.n_valid, self.rows_valid) = sums["moments"], sums["counts"]
        d = (len(m) - 1) // 2
        self.s, self.mean, scale = s, m[1 : n_features + 1], np.sqrt(m[d + 1 :] / max(m[0], 1))
        scale = scale[:n_features]
        self.feature_scale = np.where(scale < 1e-9, 1.0, scale)
        self.scale = np.concatenate([self.feature_scale, np.ones(d - n_features)])
        # Weak labels together weigh `weak_weight` times the seeds.
        self.weak = s.weak_weight * (self.n_train / all_weak if all_weak and self.n_train else 1.0)
        self.total = max(self.n_train + self.weak * self.n_weak, 1e-9)
        self.taught = self.n_train + self.n_weak > 0
        ridges = [l2 * np.concatenate([np.ones(n_features), np.full(d - n_features, r)]) for l2 in s.l2_grid for r in (s.source_ridges if d > n_features else (1.0,))]
        self.ridges = ridges if self.n_valid else ridges[len(ridges) // 2 :][:1]
        self.middle = self.ridges[len(self.ridges) // 2]
        self.lead = Search(start * self.scale, 1e-8) if self.taught else None
        self.searches: list[Search] = []
        self.chosen, self.last, self.platt, self.ab = None, None, None, (1.0, 0.0)

    def _inverse(self, ridge: np.ndarray) -> np.ndarray:
        return np.linalg.inv(self.h + np.diag(ridge)) if self.h.ndim == 2 else 1 / (self.h + ridge)

    def follow(self) -> None:
        """All ridges go on from the middle one, whose curvature they share."""
        self.searches = [Search(self.lead.w, 1e-11, self._inverse(r)) for r in self.ridges]

    def told(self, searches: list[Search], ridges: list[np.ndarray], total: float, slopes: np.ndarray, curve: np.ndarray | None) -> None:
        v, d = slopes.reshape(1 + len(self.scale), len(searches)), len(self.scale)
        if curve is not None:
            self.h = curve.reshape(d, d) / np.outer(self.scale, self.scale) / total if d <= DENSE else curve / self.scale**2 / total
        for i, (one, ridge) in enumerate(zip(searches, ridges, strict=True)):
            w = one.trial
            one.tell(v[0, i] / total + (ridge * w) @ w / 2, v[1:, i] / self.scale / total + ridge * w, None if curve is None else self._inverse(ridge))

    def raw(self, weights: list[np.ndarray]) -> np.ndarray:
        return np.stack([w / self.scale for w in weights], axis=1)

    def choose(self, losses: np.ndarray | None) -> None:
        """The ridge of the least loss on validation cells; what is calibrated, and fitted again with these cells."""
        self.chosen = int(np.argmin(losses)) if losses is not None else 0
        self.w = self.searches[self.chosen].w
        if self.n_valid:
            self.last = Search(self.w, 1e-12)
            if self.s.calibrate == "platt" and self.rows_valid > self.n_valid:
                self.platt = _Platt()

    def got(self) -> dict:
        out = {"mean": self.mean.tolist(), "scale": self.feature_scale.tolist()}
        if not self.taught:
            return {"w": [0.0] * len(self.scale), **out, "l2": self.s.l2_grid[0], "a": 1.0, "b": 0.0}
        a, b = self.ab
        if self.platt is not None and self.platt.at[0] > 0:
            a, b = map(float, self.platt.at)
        return {"w": (self.last.w if self.last is not None else self.w).tolist(), **out, "l2": float(self.ridges[self.chosen][0]), "a": a, "b": b}


def fit(passed: Callable[[Work, set[str] | None, bool], dict[tuple[str, str], np.ndarray]], settings: Callable[[str], object], start: Callable[[str, int], np.ndarray]) -> dict[str, dict]:
    """Models by key.  passed: makes a pass of some work over the lessons of some models (or all), of validation cells alone if so told;
    start: a model's raw weights to begin with, near the answer or not, from its key and number of weights."""

    def first(key: str, lesson: Lesson):
        n, mean = len(lesson.x), lesson.x.mean(axis=0)
        yield "moments", np.concatenate([[n], mean, ((lesson.x - mean) ** 2).sum(axis=0)])
        valid = (lesson.role == VALIDATION) & lesson.has
        yield "counts", np.array([((lesson.role == TRAIN) & lesson.has).sum(), ((lesson.role == WEAK) & lesson.has).sum(), (lesson.role == WEAK).sum(), valid.sum(), lesson.size[valid].sum()], float)
        yield "features", np.array([1.0, lesson.n_features])

    sums = passed(first, None, False)
    models: dict[str, _Model] = {}
    for key in sorted({k for k, _ in sums}):
        mine = {name: v for (k, name), v in sums.items() if k == key}
        n_features = round(mine["features"][1] / mine["features"][0])
        models[key] = _Model(settings(key), n_features, start(key, (len(mine["moments"]) - 1) // 2), mine)

    def descend(asked: dict[str, tuple[list[Search], list[np.ndarray], float]], valid: bool, bent: bool) -> None:
        """One pass for the searches that aren't done; with the curvature, at one search a model, if bent."""
        trial = {k: models[k].raw([one.trial for one in found]) for k, (found, _, _) in asked.items()}
        weak = {k: models[k].weak for k in asked}

        def slopes(key: str, lesson: Lesson):
            some = lesson.cells(lesson.has & (lesson.size > 1) & (valid | (lesson.role != VALIDATION)))  # a cell of one candidate has no slope
            weight = np.where(some.role == WEAK, weak[key], 1.0)
            yield "slopes", some.slopes(trial[key], weight)
            if bent:
                yield "curve", some.curvature(trial[key][:, 0], weight)

        found = passed(slopes, set(asked), False)
        for k, (searches, ridges, total) in asked.items():
            models[k].told(searches, ridges, total, found[k, "slopes"], found.get((k, "curve")))

    while asked := {k: ([m.lead], [m.middle], m.total) for k, m in models.items() if m.lead is not None and not m.lead.done}:
        descend(asked, False, True)
    for m in models.values():
        if m.taught:
            m.follow()
    while asked := {k: (*map(list, zip(*some, strict=True)), m.total) for k, m in models.items() if (some := [(one, r) for one, r in zip(m.searches, m.ridges, strict=False) if not one.done])}:
        descend(asked, False, False)
    taught = {k: m for k, m in models.items() if m.taught}
    several = {k: m.raw([one.w for one in m.searches]) for k, m in taught.items() if m.n_valid}
    losses = passed(lambda key, lesson: iter([("losses", lesson.cells(lesson.has & (lesson.role == VALIDATION)).losses(several[key]))]), set(several), True) if several else {}
    for k, m in taught.items():
        m.choose(losses.get((k, "losses")))
    while asked := {k: ([m.last], [m.ridges[m.chosen]], m.total + m.n_valid) for k, m in taught.items() if m.last is not None and not m.last.done}:
        descend(asked, True, True)
    said = {k: (m.w / m.scale, m.n_valid, m.rows_valid - m.n_valid) for k, m in taught.items()}
    while asked := {k: m.platt.trial for k, m in taught.items() if m.platt is not None and not m.platt.done}:

        def sigmoid(key: str, lesson: Lesson, asked=asked):
            some, (w, ones, zeros) = lesson.cells(lesson.has & (lesson.role == VALIDATION)), said[key]
            yield "platt", platt_sums(some.logits(w), np.where(some.y > 0, (ones + 1) / (ones + 2), 1 / (zeros + 2)), *asked[key])

        found = passed(sigmoid, set(asked), True)
        for k in asked:
            taught[k].platt.tell(taught[k].rows_valid, found[k, "platt"])
    warm = {k for k, m in taught.items() if m.n_valid and m.s.calibrate == "temperature"}
    if warm:

        def heat(key: str, lesson: Lesson):
            some = lesson.cells(lesson.has & (lesson.role == VALIDATION))
            z = some.logits(said[key][0])[:, None] * np.array(TEMPERATURES)
            yield "heat", -np.log(np.maximum(some.shares(z)[some.y > 0], 1e-12)).sum(axis=0) if len(z) else np.zeros(len(TEMPERATURES))

        for (k, _), v in passed(heat, warm, True).items():
            taught[k].ab = (TEMPERATURES[int(np.argmin(v))], 0.0)
    return {k: m.got() for k, m in models.items()}
