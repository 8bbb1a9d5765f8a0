"""Classifiers: softmax by Newton, Adam or MLlib; conditional softmax over candidates; Platt calibration."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def softmax_rows(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def adam_softmax(x: np.ndarray, y: np.ndarray, n_slots: int, weight: np.ndarray | None = None, epochs: int = 500, batch: int = 10, rate: float = 0.01, l2: float = 1e-3, seed: int = 0) -> np.ndarray:
    """(features + 1) x slots weights, the last row the constant, by Adam on cross-entropy in small batches."""
    rng = np.random.default_rng(seed)
    x = np.hstack([x, np.ones((len(x), 1))])
    weight = np.ones(len(x)) if weight is None else weight
    w = np.zeros((x.shape[1], n_slots))
    m, v, t = np.zeros_like(w), np.zeros_like(w), 0
    g, a, b = np.empty_like(w), np.empty_like(w), np.empty_like(w)  # a step makes no table anew
    hot = np.eye(n_slots)[y]
    for _ in range(epochs):
        order = rng.permutation(len(x))
        xs, hs, ws = x[order], hot[order], weight[order, None]  # a batch is a slice
        for lo in range(0, len(x), batch):
            xb = xs[lo : lo + batch]
            p = xb @ w
            p -= p.max(axis=1, keepdims=True)
            np.exp(p, out=p)
            p /= p.sum(axis=1, keepdims=True)
            p -= hs[lo : lo + batch]
            p *= ws[lo : lo + batch]
            p /= len(xb)
            np.matmul(xb.T, p, out=g)
            g += np.multiply(w, l2, out=a)
            t += 1
            m *= 0.9
            m += np.multiply(g, 0.1, out=a)
            v *= 0.999
            g *= g
            v += np.multiply(g, 0.001, out=a)
            # The corrections of both means are numbers: they are taken out of the tables.
            second = (1 - 0.999**t) ** 0.5
            np.sqrt(v, out=b)
            b += 1e-8 * second
            np.divide(m, b, out=a)
            a *= rate * second / (1 - 0.9**t)
            w -= a
    return w


def gradient_softmax(x: np.ndarray, y: np.ndarray, n_slots: int, weight: np.ndarray | None = None, l2: float = 1e-2, rounds: int = 200) -> np.ndarray:
    """The same model by full-batch gradient steps with momentum and backtracking."""
    x = np.hstack([x, np.ones((len(x), 1))])
    weight = np.ones(len(x)) if weight is None else weight
    hot, total = np.eye(n_slots)[y], weight.sum()

    def loss(w):
        p = softmax_rows(x @ w)
        return -(weight * np.log(np.maximum(p[np.arange(len(y)), y], 1e-12))).sum() / total + l2 * (w * w).sum() / 2

    w = np.zeros((x.shape[1], n_slots))
    step, last = 1.0, loss(w)
    for _ in range(rounds):
        g = x.T @ ((softmax_rows(x @ w) - hot) * weight[:, None]) / total + l2 * w
        if np.abs(g).max() < 1e-6:
            break
        while step > 1e-8:
            new = w - step * g
            now = loss(new)
            if now <= last - 0.25 * step * (g * g).sum():
                break
            step /= 2
        w, last, step = new, now, step * 1.5
    return w


def sigmoid_rows(z: np.ndarray) -> np.ndarray:
    """Independent probabilities of the columns, scaled to sum to 1 in a row."""
    p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
    return p / p.sum(axis=1, keepdims=True)


def one_vs_rest(x: np.ndarray, y: np.ndarray, n_slots: int, weight: np.ndarray | None = None, l2: float = 1e-2, rounds: int = 30) -> np.ndarray:
    """(features + 1) x slots weights, one logistic model a slot, by Newton's method."""
    x = np.hstack([x, np.ones((len(x), 1))])
    weight = np.ones(len(x)) if weight is None else weight
    total = weight.sum()
    w = np.zeros((x.shape[1], n_slots))
    for k in range(n_slots):
        t = (y == k).astype(float)
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(x @ w[:, k], -30, 30)))
            g = x.T @ (weight * (p - t)) / total + l2 * w[:, k]
            h = (x * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ x / total + l2 * np.eye(x.shape[1])
            step = np.clip(np.linalg.solve(h, g), -5, 5)
            w[:, k] -= step
            if np.abs(step).max() < 1e-6:
                break
    return w


def tree_fit(x: np.ndarray, y: np.ndarray, n_slots: int, weight: np.ndarray | None = None, depth: int = 6, least: int = 5) -> list:
    """A decision tree by Gini impurity, as nested lists: [feature, threshold, left, right], or [shares of the slots]."""
    weight = np.ones(len(x)) if weight is None else weight
    shares = np.bincount(y, weights=weight, minlength=n_slots) + 1e-3
    leaf = [(shares / shares.sum()).tolist()]
    if depth == 0 or len(y) < 2 * least or (y == y[0]).all():
        return leaf
    hot, best = np.eye(n_slots)[y] * weight[:, None], None
    for j in range(x.shape[1]):
        order = np.argsort(x[:, j], kind="stable")
        v, left = x[order, j], hot[order].cumsum(axis=0)
        cut = np.flatnonzero(v[1:] > v[:-1])
        cut = cut[(cut + 1 >= least) & (len(y) - cut - 1 >= least)]
        if not len(cut):
            continue
        a, b = left[cut], left[-1] - left[cut]
        gain = (a**2).sum(axis=1) / np.maximum(a.sum(axis=1), 1e-12) + (b**2).sum(axis=1) / np.maximum(b.sum(axis=1), 1e-12)
        k = int(gain.argmax())
        if best is None or gain[k] > best[0] + 1e-12:
            best = (gain[k], j, float((v[cut[k]] + v[cut[k] + 1]) / 2))
    total = hot.sum(axis=0)
    if best is None or best[0] <= (total**2).sum() / total.sum() + 1e-9:
        return leaf
    _, j, at = best
    low = x[:, j] <= at
    return [j, at, tree_fit(x[low], y[low], n_slots, weight[low], depth - 1, least), tree_fit(x[~low], y[~low], n_slots, weight[~low], depth - 1, least)]


def tree_rows(x: np.ndarray, tree: list) -> np.ndarray:
    """The shares of each row's leaf."""
    if len(tree) == 1:
        return np.tile(np.array(tree[0]), (len(x), 1))
    j, at, left, right = tree
    low = x[:, j] <= at
    a, b = tree_rows(x[low], left), tree_rows(x[~low], right)
    out = np.empty((len(x), (a if len(a) else b).shape[1]))
    out[low], out[~low] = a, b
    return out


def conditional_softmax(x: np.ndarray, y: np.ndarray, group: np.ndarray, weight: np.ndarray, l2: float | np.ndarray, rounds: int = 25, start: np.ndarray | None = None) -> np.ndarray:
    """Shared weights for candidates that compete within their group, by Newton's method.

    x: candidates by features; y: 1 for the truth; group: dense numbers, sorted;
    weight: of each group; l2: one ridge, or one for each feature.  Groups without
    a truth must be left out before.  start: weights near the answer, of another ridge;
    there is one answer, whatever the start.
    """
    l2 = np.broadcast_to(np.asarray(l2, dtype=float), x.shape[1])
    starts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    size = np.diff(np.append(starts, len(group)))
    of = np.repeat(np.arange(len(starts)), size)
    gw = weight[starts]
    total = max(gw.sum(), 1e-9)
    w = np.zeros(x.shape[1]) if start is None else start

    def probabilities(v: np.ndarray) -> np.ndarray:
        z = x @ v
        z = z - np.maximum.reduceat(z, starts)[of]
        e = np.exp(z)
        return e / np.add.reduceat(e, starts)[of]

    def loss(v: np.ndarray) -> tuple[float, np.ndarray]:
        p = probabilities(v)
        true = np.add.reduceat(p * y, starts)
        return -(gw * np.log(np.maximum(true, 1e-12))).sum() / total + (l2 * v) @ v / 2, p

    last, p = loss(w)
    for _ in range(rounds):
        g = ((p - y) * gw[of]) @ x / total + l2 * w
        mean = np.add.reduceat(x * p[:, None], starts, axis=0)
        h = (x * (p * gw[of])[:, None]).T @ x - (mean * gw[:, None]).T @ mean
        h = h / total + np.diag(l2)
        step = np.linalg.solve(h, g)
        if g @ step < 1e-12:  # nearer to the answer than the loss can tell: the whole step, which rounding mustn't cut
            return w - step
        scale = 1.0
        now, q = loss(w - scale * step)
        while now > last - 1e-4 * scale * (g @ step) and scale > 1e-4:
            scale /= 2
            now, q = loss(w - scale * step)
        w, p = w - scale * step, q
        if last - now < 1e-9:
            break
        last = now
    return w


def platt_fit(score: np.ndarray, y: np.ndarray, epochs: int = 50, rate: float = 0.5, weight: np.ndarray | None = None) -> tuple[float, float]:
    """(a, b) of sigmoid(a * score + b), by Newton steps on log-loss; (1, 0) where one label is missing; weight counts repeated rows.

    A step that raises the loss is cut: where few rows bend the loss, whole steps lead ever farther away.
    """
    if len(score) == 0 or y.min() == y.max():
        return 1.0, 0.0
    weight = np.ones(len(score)) if weight is None else weight
    total, at, best = weight.sum(), np.array([1.0, 0.0]), None
    for _ in range(epochs):
        f, g, h = platt_step(platt_sums(score, y, *at, weight), total, *at)
        if best is not None and f > best[0] + 1e-15 and scale > 1e-6:
            scale /= 2
        else:
            best, scale = (f, at, np.linalg.solve(h, g)), rate
        at = best[1] - scale * best[2]
    return float(at[0]), float(at[1])


def platt_sums(score: np.ndarray, y: np.ndarray, a: float, b: float, weight: np.ndarray | float = 1.0) -> np.ndarray:
    """Sums over rows that a step needs: the log-loss, its slope in a and b, its curvature in aa, ab and bb."""
    z = np.clip(a * score + b, -30, 30)
    p = 1 / (1 + np.exp(-z))
    r, s = (p - y) * weight, np.maximum(p * (1 - p), 1e-9) * weight
    return np.array([(weight * (np.logaddexp(0, z) - y * z)).sum(), (r * score).sum(), r.sum(), (s * score * score).sum(), (s * score).sum(), s.sum()])


def platt_step(sums: np.ndarray, total: float, a: float, b: float) -> tuple[float, np.ndarray, np.ndarray]:
    """Loss, slope and curvature of the mean, with a ridge that holds a near 1."""
    f, ga, gb, aa, ab, bb = sums / total
    return f + 0.5e-4 * (a - 1) ** 2, np.array([ga + 1e-4 * (a - 1), gb]), np.array([[aa + 1e-4, ab], [ab, bb + 1e-9]])


def platt_apply(score, a: float, b: float):
    return 1 / (1 + F.exp(-(F.lit(a) * score + F.lit(b))))


def mllib(df: DataFrame, features: str, label: str, classifier: str = "softmax", l2: float = 0.01, max_iter: int = 100):
    """A fitted MLlib model over a vector column: softmax (L-BFGS), one-vs-rest, or a decision tree."""
    from pyspark.ml.classification import DecisionTreeClassifier, LogisticRegression, OneVsRest

    if classifier == "softmax":
        made = LogisticRegression(featuresCol=features, labelCol=label, family="multinomial", regParam=l2, maxIter=max_iter)
    elif classifier == "logreg_ovr":
        made = OneVsRest(featuresCol=features, labelCol=label, classifier=LogisticRegression(regParam=l2, maxIter=max_iter))
    elif classifier == "tree":
        made = DecisionTreeClassifier(featuresCol=features, labelCol=label, maxDepth=8)
    else:
        raise ValueError("classifier must be softmax, logreg_ovr or tree")
    return made.fit(df)
