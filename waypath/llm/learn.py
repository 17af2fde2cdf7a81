"""Small learners fitted on a bounded sample: histogram trees, isotonic steps, ranked pairs."""

from __future__ import annotations

import numpy as np


def sigmoid(z):
    return 1.0 / (1.0 + np.exp(-np.clip(z, -35, 35)))


class Trees:
    """Gradient-boosted trees for a 0/1 label: depth-limited, second-order gains over feature bins."""

    def __init__(self, rounds=80, depth=3, rate=0.15, bins=32, least=8, ridge=1.0):
        self.rounds, self.depth, self.rate, self.bins, self.least, self.ridge = rounds, depth, rate, bins, least, ridge

    def fit(self, x: np.ndarray, y: np.ndarray) -> "Trees":
        n, f = x.shape
        self.cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins + 1)[1:-1])) if n else np.zeros(0) for j in range(f)]
        codes = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(self.cuts)], 1) if f else np.zeros((n, 0), int)
        width = self.bins + 1
        flat = codes + np.arange(f) * width
        p = np.clip(y.mean() if n else 0.5, 1e-3, 1 - 1e-3)
        self.base = float(np.log(p / (1 - p)))
        z = np.full(n, self.base)
        self.trees = []
        for _ in range(self.rounds):
            prob = sigmoid(z)
            g, h = y - prob, np.maximum(prob * (1 - prob), 1e-6)
            node = np.zeros(n, int)
            split = {}
            for level in range(self.depth):
                first, k = 2**level - 1, 2**level
                local = node - first
                key = (local[:, None] * (f * width) + flat).ravel()
                gs = np.bincount(key, np.repeat(g, f), k * f * width).reshape(k, f, width).cumsum(2)
                hs = np.bincount(key, np.repeat(h, f), k * f * width).reshape(k, f, width).cumsum(2)
                cs = np.bincount(key, minlength=k * f * width).reshape(k, f, width).cumsum(2)
                gt, ht, ct = gs[..., -1:], hs[..., -1:], cs[..., -1:]
                gain = gs**2 / (hs + self.ridge) + (gt - gs) ** 2 / (ht - hs + self.ridge) - gt**2 / (ht + self.ridge)
                gain[(cs < self.least) | (ct - cs < self.least)] = -1
                best = gain.reshape(k, -1).argmax(1)
                value = gain.reshape(k, -1).max(1)
                feat, at = best // width, best % width
                ok = (value > 1e-4) & (at < np.array([len(c) for c in self.cuts])[feat])
                for i in range(k):
                    split[first + i] = (int(feat[i]), float(self.cuts[feat[i]][at[i]])) if ok[i] else (0, np.inf)
                fs, ts = np.array([split[first + i][0] for i in range(k)]), np.array([split[first + i][1] for i in range(k)])
                node = 2 * node + 1 + (x[np.arange(n), fs[local]] > ts[local])
            leaves = 2**self.depth
            leaf = node - (leaves - 1)
            val = np.bincount(leaf, g, leaves) / (np.bincount(leaf, h, leaves) + self.ridge) * self.rate
            inner = np.array([split[i] for i in range(leaves - 1)])
            self.trees.append((inner[:, 0].astype(int), inner[:, 1], val))
            z += val[leaf]
        return self

    def raw(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for feat, cut, val in self.trees:
            node = np.zeros(len(x), int)
            for _ in range(self.depth):
                node = 2 * node + 1 + (x[rows, feat[node]] > cut[node])
            z += val[node - (len(val) - 1)]
        return z


class Isotonic:
    """Pooled adjacent violators, then straight lines between the pools' centres so order survives.

    A fiftieth of the result is the logistic of the raw score, which keeps rows of one pool
    in order; the calibrated probability moves by 0.02 at most.
    """

    def fit(self, score: np.ndarray, y: np.ndarray) -> "Isotonic":
        order = np.argsort(score, kind="stable")
        pools = []
        for s, t in zip(score[order], y[order].astype(float)):
            pools.append([t, 1.0, s])
            while len(pools) > 1 and pools[-2][0] >= pools[-1][0]:
                t2, w2, s2 = pools.pop()
                t1, w1, s1 = pools[-1]
                pools[-1] = [(t1 * w1 + t2 * w2) / (w1 + w2), w1 + w2, (s1 * w1 + s2 * w2) / (w1 + w2)]
        self.at = np.array([p[2] for p in pools] or [0.0])
        self.value = np.array([p[0] for p in pools] or [0.5])
        return self

    def __call__(self, score: np.ndarray) -> np.ndarray:
        return 0.98 * np.interp(score, self.at, self.value) + 0.02 * sigmoid(score)


class BradleyTerry:
    """A document's strength is linear in its features; good ones should win against bad ones.

    Each good row meets ``meetings`` bad ones and each bad one as many good ones; the
    logistic loss on the feature differences is minimised by Newton's steps with a ridge.
    """

    def __init__(self, meetings=8, ridge=1e-2, steps=25, seed=11):
        self.meetings, self.ridge, self.steps, self.seed = meetings, ridge, steps, seed

    def fit(self, x: np.ndarray, y: np.ndarray) -> "BradleyTerry":
        self.mean = x.mean(0) if len(x) else np.zeros(x.shape[1])
        self.scale = x.std(0) + 1e-9 if len(x) else np.ones(x.shape[1])
        xs = np.clip((x - self.mean) / self.scale, -8, 8)
        self.w = np.zeros(x.shape[1])
        good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
        if not len(good) or not len(bad):
            return self
        rng = np.random.default_rng(self.seed)
        a = np.r_[np.repeat(good, self.meetings), rng.choice(good, len(bad) * self.meetings)]
        b = np.r_[rng.choice(bad, len(good) * self.meetings), np.repeat(bad, self.meetings)]
        d = xs[a] - xs[b]
        for _ in range(self.steps):
            p = sigmoid(d @ self.w)
            grad = d.T @ (1 - p) / len(d) - self.ridge * self.w
            hess = (d * (p * (1 - p))[:, None]).T @ d / len(d) + self.ridge * np.eye(len(self.w))
            step = np.linalg.solve(hess, grad)
            self.w += step
            if np.abs(step).max() < 1e-7:
                break
        return self

    def strength(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -8, 8) @ self.w
