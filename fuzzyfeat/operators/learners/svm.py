"""Kernel machines, one pair of classes against another: over the exact monomial map, on the kernel matrix itself, or over Nystroem landmarks or random cosine features.

Each pair minimises half the squared weights plus C times the squared hinge losses, by Newton steps. Unless a map is asked
for by name, the machine is exact as long as that is affordable: the monomial map up to EXPLICIT_WIDTH columns, the kernel
matrix up to EXACT_ROWS rows. Beyond both it is a Nystroem approximation, and `approximate` says so.
Symbolic columns enter as one column per level; all inputs are min-max scaled inside; unknowns are 0.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations, combinations_with_replacement
from math import comb, factorial

import numpy as np

from fuzzyfeat.operators.learners.data import Frame


EXPLICIT_WIDTH, EXACT_ROWS = 600, 1500
BLOCK, HELD = 8192, 16_000_000  # rows that are mapped at a time, and numbers of a map that are kept rather than worked out at each step


class KernelSVM:
    def __init__(self, kernel: str = "poly", degree: int = 2, gamma: float = 0.1, C: float = 1.0, approx: str | None = None, features: int = 256, homogeneous: bool = False, multiclass: str = "ovo", seed: int = 11):
        self.kernel, self.degree, self.gamma, self.C, self.features, self.homogeneous, self.multiclass, self.seed = kernel, degree, gamma, C, features, homogeneous, multiclass, seed
        self.asked = self.approx = approx

    @property
    def approximate(self) -> bool:
        return self.approx in ("nystrom", "rff")

    def choose(self, rows: int, width: int) -> str:
        if self.kernel == "poly" and comb(width + (0 if self.homogeneous else 1) + self.degree - 1, self.degree) <= EXPLICIT_WIDTH:
            return "explicit"
        return "exact" if rows <= EXACT_ROWS else "nystrom"

    def _inputs(self, frame: Frame) -> np.ndarray:
        with np.errstate(divide="ignore", invalid="ignore"):
            x = np.where(self.high > self.low, (frame.num - self.low) / np.where(self.high > self.low, self.high - self.low, 1), 0)
        hot = [(frame.cat[:, j][:, None] == np.arange(n)[None, :]).astype(float) for j, n in enumerate(self.levels)]
        return np.nan_to_num(np.concatenate([x, *hot], axis=1))

    def gram(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if self.kernel == "poly":
            return (a @ b.T + (0 if self.homogeneous else 1)) ** self.degree
        return np.exp(-self.gamma * np.maximum(0, (a**2).sum(1)[:, None] + (b**2).sum(1)[None, :] - 2 * a @ b.T))

    def monomials(self, x: np.ndarray) -> np.ndarray:
        """The exact map of the polynomial kernel: monomials times the roots of their multinomial coefficients."""
        if not self.homogeneous:
            x = np.concatenate([np.ones((len(x), 1)), x], axis=1)
        columns = []
        for combo in combinations_with_replacement(range(x.shape[1]), self.degree):
            coefficient = factorial(self.degree)
            for j in set(combo):
                coefficient //= factorial(combo.count(j))
            columns.append(np.sqrt(coefficient) * x[:, list(combo)].prod(axis=1))
        return np.stack(columns, axis=1)

    def _map(self, x: np.ndarray) -> np.ndarray:
        if self.approx == "explicit":
            z = self.monomials(x)
        elif self.approx == "rff":
            z = np.sqrt(2 / self.features) * np.cos(x @ self.directions + self.phases)
        else:
            z = self.gram(x, self.landmarks) @ self.whiten
        return np.concatenate([z, np.ones((len(z), 1))], axis=1)

    def scale(self, n_classes: int, low: np.ndarray, high: np.ndarray, levels: list[int], sizes: np.ndarray) -> None:
        """What the inputs' map and the votes need of the training rows: extremes, numbers of levels, class sizes."""
        self.n_classes, self.low, self.high, self.levels = n_classes, low, high, levels
        self.present = [c for c in range(n_classes) if sizes[c]]
        self.only = self.present[0] if len(self.present) == 1 else None
        self.prior = sizes / max(1, sizes.sum())
        # -1: against all other classes
        self.pairs = list(combinations(self.present, 2)) if self.multiclass == "ovo" else [(a, -1) for a in self.present]

    def basis(self, frame: Frame, y: np.ndarray) -> None:
        """The approximate maps' directions, or their landmarks: the given rows."""
        x = self._inputs(frame)
        if self.approx == "rff":
            g = np.random.default_rng(self.seed)
            self.directions = g.standard_normal((x.shape[1], self.features)) * np.sqrt(2 * self.gamma)
            self.phases = g.uniform(0, 2 * np.pi, self.features)
        elif self.approx == "nystrom":
            self.landmarks = np.unique(x, axis=0)
            values, vectors = np.linalg.eigh(self.gram(self.landmarks, self.landmarks))
            keep = values > values.max() * 1e-9
            self.whiten = vectors[:, keep] / np.sqrt(values[keep])

    def mapped(self, frame: Frame) -> np.ndarray:
        return self._map(self._inputs(frame))

    def columns(self, empty: Frame) -> int:
        return self.mapped(empty).shape[1]

    def fit(self, frame: Frame, y: np.ndarray, n_classes: int, weights: np.ndarray | None = None) -> "KernelSVM":
        with np.errstate(all="ignore"):
            low, high = (np.nan_to_num(f(np.where(np.isnan(frame.num), fill, frame.num), axis=0)) if len(frame) else np.zeros(frame.num.shape[1]) for f, fill in ((np.min, np.inf), (np.max, -np.inf)))
        self.scale(n_classes, low, high, [int(frame.cat[:, j].max(initial=-1)) + 1 for j in range(frame.cat.shape[1])], np.bincount(y, minlength=n_classes))
        x = self._inputs(frame)
        self.approx = self.asked or self.choose(*x.shape)
        if self.approx == "nystrom":
            g, per = np.random.default_rng(self.seed), max(1, self.features // max(1, len(self.present)))
            picks = np.concatenate([g.permutation(np.flatnonzero(y == c))[:per] for c in self.present])
            self.basis(frame.rows(picks), y[picks])
        else:
            self.basis(frame.rows(np.zeros(0, np.int64)), y[:0])
        self.models, targets = [], []
        for a, b in self.pairs:
            rows = np.flatnonzero((y == a) | (y == b)) if b >= 0 else np.arange(len(y))
            targets.append((rows, np.where(y[rows] == a, 1.0, -1.0), None if weights is None else weights[rows]))
        if self.approx == "exact":
            found = []
            for rows, target, own in targets:
                beta, constant = kernel_newton(self.gram(x[rows], x[rows]), target, self.C, own)
                found.append((x[rows][beta != 0], beta[beta != 0], constant))
        else:
            width = self.columns(frame.rows(np.zeros(0, np.int64)))
            held = self._map(x) if len(x) * width <= HELD else None
            found = newton_pairs((lambda i, j: held[i:j]) if held is not None else (lambda i, j: self._map(x[i:j])), len(x), width, targets, self.C)
        self.models = [(a, b if b >= 0 else None, w) for (a, b), w in zip(self.pairs, found, strict=True)]
        return self

    def predict(self, frame: Frame) -> np.ndarray:
        if self.only is not None:
            return np.full(len(frame), self.only)
        x = self._inputs(frame)
        z = self._map(x) if self.approx != "exact" else x
        votes = np.zeros((len(frame), self.n_classes)) + 0.5 * self.prior
        for a, b, w in self.models:
            f = z @ w if self.approx != "exact" else self.gram(z, w[0]) @ w[1] + w[2]
            if b is None:
                votes[:, a] += f * 1e3
            else:
                votes[:, a] += f > 0
                votes[:, b] += f <= 0
        return votes.argmax(axis=1)


def newton(z: np.ndarray, t: np.ndarray, C: float, weights: np.ndarray | None = None, steps: int = 12) -> np.ndarray:
    """Weights of the squared-hinge machine for targets of +-1; the last column of z is the unpenalised constant."""
    return newton_pairs(lambda i, j: z[i:j], len(z), z.shape[1], [(np.arange(len(t)), t, weights)], C, steps)[0]


def newton_pairs(mapped: Callable[[int, int], np.ndarray], n: int, d: int, targets: list[tuple], C: float, steps: int = 12) -> list[np.ndarray]:
    """The same for several machines (rows, targets, weights) over shared rows, of which mapped(i, j) gives a block.

    A step solves with the rows inside the margin of the step before; sums over these are kept, and only the rows that
    have come or gone are added or taken away.
    """
    ridge = np.eye(d) / 2
    ridge[-1, -1] = 0.5e-8
    squares, crosses, found = [np.zeros((d, d)) for _ in targets], [np.zeros(d) for _ in targets], [np.zeros(d) for _ in targets]
    active, live = [np.zeros(len(t), bool) for _, t, _ in targets], set(range(len(targets)))
    for step in range(steps + 1):
        moved = dict.fromkeys(live, 0)
        for i in range(0, n, BLOCK):
            z = mapped(i, min(n, i + BLOCK))
            for p in live:
                rows, t, weights = targets[p]
                low, high = np.searchsorted(rows, (i, i + BLOCK))
                at, tt = rows[low:high] - i, t[low:high]
                now = np.ones(len(tt), bool) if step == 0 else tt * (z @ found[p])[at] < 1
                for sign, some in ((1, now & ~active[p][low:high]), (-1, active[p][low:high] & ~now)):
                    if some.any():
                        c = sign * C * (np.ones(some.sum()) if weights is None else weights[low:high][some])
                        za = z[at[some]]
                        squares[p] += (za * c[:, None]).T @ za if weights is not None else sign * C * (za.T @ za)
                        crosses[p] += za.T @ (tt[some] * c)
                        moved[p] += int(some.sum())
                active[p][low:high] = now
        live = {p for p in live if moved[p] or step == 0}
        if not live or step == steps:
            break
        for p in live:
            found[p] = np.linalg.solve(ridge + squares[p], crosses[p])
    return found


def kernel_newton(gram: np.ndarray, t: np.ndarray, C: float, weights: np.ndarray | None = None, steps: int = 30) -> tuple[np.ndarray, float]:
    """The same machine on the kernel matrix: coefficients of the rows and the constant. Rows beyond the margin have 0."""
    n = len(t)
    c = 2 * C * (np.ones(n) if weights is None else weights)
    active, beta, constant = c > 0, np.zeros(n), 0.0
    for _ in range(steps):
        at = np.flatnonzero(active)
        system = np.zeros((len(at) + 1, len(at) + 1))
        system[:-1, :-1] = gram[np.ix_(at, at)] + np.diag(1 / c[at])
        system[:-1, -1] = system[-1, :-1] = 1
        solved = np.linalg.solve(system, np.append(t[at], 0.0))
        beta, constant = np.zeros(n), float(solved[-1])
        beta[at] = solved[:-1]
        now = (t * (gram @ beta + constant) < 1) & (c > 0)
        if (now == active).all() or not now.any():
            break
        active = now
    return beta, constant
