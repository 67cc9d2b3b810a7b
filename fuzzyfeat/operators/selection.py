"""Feature selection: correlation-based subset merit with a genetic or exhaustive search, ranking filters and a wrapper."""

from __future__ import annotations

from itertools import combinations

import numpy as np

from fuzzyfeat.operators.learners.data import Frame, edges_of, entropy


def merit(subset: list[int], to_class: np.ndarray, mutual: np.ndarray) -> float:
    """r * mean association with the class / sqrt(r + r (r - 1) * mean mutual association); 0 for the empty subset."""
    r = len(subset)
    if not r:
        return 0.0
    rest = mutual[np.ix_(subset, subset)]
    average = (rest.sum() - np.trace(rest)) / (r * (r - 1)) if r > 1 else 0.0
    return float(r * to_class[subset].mean() / np.sqrt(r + r * (r - 1) * average))


def uncertainty(a: np.ndarray, b: np.ndarray) -> float:
    """Symmetrical uncertainty of two code columns; negative codes are unknown and left out."""
    known = (a >= 0) & (b >= 0)
    if not known.any():
        return 0.0
    a, b = a[known], b[known]
    table = np.bincount(a * (b.max() + 1) + b, minlength=(a.max() + 1) * (b.max() + 1)).reshape(a.max() + 1, b.max() + 1)
    ha, hb, hj = entropy(table.sum(1)), entropy(table.sum(0)), entropy(table.reshape(-1))
    return float(2 * (ha + hb - hj) / (ha + hb)) if ha + hb > 1e-12 else 0.0


def association(frame: Frame, y: np.ndarray, bins: int = 10) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Names, associations with the class, and the matrix of mutual associations."""
    codes = [np.where(np.isnan(frame.num[:, j]), -1, np.searchsorted(edges_of(frame.num[:, j], bins), frame.num[:, j], "left")) for j in range(frame.num.shape[1])] + [frame.cat[:, j] for j in range(frame.cat.shape[1])]
    m = len(codes)
    mutual = np.eye(m)
    for i in range(m):
        for j in range(i):
            mutual[i, j] = mutual[j, i] = uncertainty(codes[i], codes[j])
    return frame.num_names + frame.cat_names, np.array([uncertainty(c, y) for c in codes]), mutual


def exhaustive(to_class: np.ndarray, mutual: np.ndarray) -> tuple[list[int], float]:
    """The best subset of at most 20 features; ties go to the smaller, earlier one."""
    m = len(to_class)
    if m > 20:
        raise ValueError("an exhaustive search is for 20 features at most")
    options = ((merit(list(s), to_class, mutual), -r, s) for r in range(1, m + 1) for s in combinations(range(m), r))
    best = max(options, key=lambda x: (round(x[0], 12), x[1], tuple(-i for i in x[2])))
    return list(best[2]), best[0]


def genetic(to_class: np.ndarray, mutual: np.ndarray, population: int = 20, generations: int = 20, crossover: float = 0.6, mutation: float = 0.033, seed: int = 42) -> tuple[list[int], float]:
    """Bit-string evolution: fitness-proportional parents, one-point crossover, bit flips, and the best always survives."""
    m, g = len(to_class), np.random.default_rng(seed)
    bits = g.random((population, m)) < 0.5
    bits[0] = True
    fitness = lambda b: np.array([merit(list(np.flatnonzero(x)), to_class, mutual) for x in b])
    score = fitness(bits)
    for _ in range(generations):
        weight = score - score.min() + 1e-9
        parents = bits[g.choice(population, population, p=weight / weight.sum())]
        children = parents.copy()
        for i in range(0, population - 1, 2):
            if m > 1 and g.random() < crossover:
                at = g.integers(1, m)
                children[i, at:], children[i + 1, at:] = parents[i + 1, at:], parents[i, at:]
        children ^= g.random(children.shape) < mutation
        children[0] = bits[score.argmax()]
        bits, score = children, fitness(children)
    best = list(np.flatnonzero(bits[score.argmax()])) or [int(to_class.argmax())]
    return best, merit(best, to_class, mutual)


class CfsSelector:
    def __init__(self, search: str = "genetic", bins: int = 10, **options):
        self.search, self.bins, self.options = search, bins, options

    def select(self, frame: Frame, y: np.ndarray, n_classes: int) -> list[str]:
        return self.choose(*association(frame, y, self.bins))

    def choose(self, names: list[str], to_class: np.ndarray, mutual: np.ndarray) -> list[str]:
        """The subset, from associations counted anywhere."""
        best, _ = (genetic if self.search == "genetic" else exhaustive)(to_class, mutual, **self.options)
        return [names[i] for i in sorted(best)]


class FilterSelector:
    """The `top` features by symmetrical uncertainty with the class."""

    def __init__(self, top: int = 5, bins: int = 10):
        self.top, self.bins = top, bins

    def select(self, frame: Frame, y: np.ndarray, n_classes: int) -> list[str]:
        return self.choose(*association(frame, y, self.bins))

    def choose(self, names: list[str], to_class: np.ndarray, mutual: np.ndarray) -> list[str]:
        return [names[i] for i in sorted(np.argsort(-to_class, kind="stable")[: self.top])]


class WrapperSelector:
    """Forward selection by the cross-validated accuracy of the inducer itself."""

    def __init__(self, make, folds: int = 3, seed: int = 1):
        self.make, self.folds, self.seed = make, folds, seed

    def select(self, frame: Frame, y: np.ndarray, n_classes: int) -> list[str]:
        fold = np.random.default_rng(self.seed).integers(0, self.folds, len(y))
        chosen: list[str] = []
        best = 0.0
        names = frame.num_names + frame.cat_names
        while len(chosen) < len(names):
            trials = []
            for name in (n for n in names if n not in chosen):
                part = frame.only([*chosen, name])
                hits = sum((self.make().fit(part.rows(np.flatnonzero(fold != f)), y[fold != f], n_classes).predict(part.rows(np.flatnonzero(fold == f))) == y[fold == f]).sum() for f in range(self.folds))
                trials.append((hits / len(y), name))
            top = max(trials, key=lambda t: t[0])
            if top[0] <= best + 1e-9:
                break
            best, chosen = top[0], [*chosen, top[1]]
        return chosen or names[:1]
