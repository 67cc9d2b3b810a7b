"""Gain-ratio trees with pessimistic pruning, and their ensembles.

A node splits symbolic features many ways and numeric ones at a threshold, by the best gain ratio among splits of at least
average gain; every split needs two branches of min_leaf rows. Unknown values go down all branches with weights in
proportion. Pruning replaces a subtree by a leaf if the upper binomial bound of the errors does not rise.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from fuzzyfeat.operators.learners.data import Frame, edges_of, entropy


def normal_quantile(p: float) -> float:
    """Inverse of the standard normal distribution by bisection."""
    low, high = -10.0, 10.0
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if 0.5 * math.erfc(-mid / math.sqrt(2)) < p else (low, mid)
    return (low + high) / 2


def upper_error(errors: float, n: float, confidence: float) -> float:
    """Upper bound of the error rate of a leaf with n rows and so many errors, at the given confidence."""
    if n <= 0:
        return 0.0
    none = 1 - confidence ** (1 / n)
    if errors < 1:
        return none + errors * (upper_error(1, n, confidence) - none) if errors > 0 else none
    if errors + 0.5 >= n:
        return 1.0
    z, f = normal_quantile(1 - confidence), (errors + 0.5) / n
    return (f + z * z / (2 * n) + z * math.sqrt(f / n - f * f / n + z * z / (4 * n * n))) / (1 + z * z / n)


@dataclass
class Node:
    counts: np.ndarray
    feature: int = -1  # numeric features first, symbolic ones after
    threshold: float = 0.0
    below: float = 0.0  # the value next to the threshold on its left
    mark: int = -1  # of a node that still grows
    children: dict[int, "Node"] = field(default_factory=dict)  # 0 and 1 of a threshold, codes of a symbolic feature

    def leaves(self) -> int:
        return sum(c.leaves() for c in self.children.values()) if self.children else 1


class C45Tree:
    """bins None: every midpoint of neighbouring values is a threshold, else quantiles; max_depth None: as deep as the rows go."""

    def __init__(self, confidence: float = 0.2, min_leaf: float = 6, bins: int | None = None, max_depth: int | None = None, prune: bool = True):
        self.confidence, self.min_leaf, self.bins, self.max_depth, self.prune = confidence, min_leaf, bins, max_depth, prune

    def fit(self, frame: Frame, y: np.ndarray, n_classes: int, weights: np.ndarray | None = None, depth: int = 0, used: frozenset = frozenset()) -> "C45Tree":
        """depth, used: where the root of a subtree stands, and the symbolic features that were split above it."""
        w = np.ones(len(y)) if weights is None else weights
        self.n_classes, self.n_num = n_classes, frame.num.shape[1]
        self.edges = [edges_of(frame.num[:, j], self.bins) for j in range(self.n_num)]
        codes = [np.where(np.isnan(frame.num[:, j]), -1, np.searchsorted(e, frame.num[:, j], "left")) for j, e in enumerate(self.edges)] + [np.maximum(frame.cat[:, j], -1) for j in range(frame.cat.shape[1])]
        self.width = [len(e) + 1 for e in self.edges] + [int(max(0, frame.cat[:, j].max(initial=-1))) + 1 for j in range(frame.cat.shape[1])]
        self._num = frame.num
        self.root = self._grow(codes, y, w, np.arange(len(y)), depth, used)
        del self._num
        if self.prune:
            self._prune(self.root)
        return self

    def _grow(self, codes, y, w, rows, depth, used) -> Node:
        counts = np.bincount(y[rows], w[rows], self.n_classes)
        node = Node(counts)
        total = counts.sum()
        if self.ends(counts, depth):
            return node
        found = []  # (gain, ratio, cut, feature)
        for f, code in enumerate(codes):
            if f in used:
                continue
            c = code[rows]
            known = c >= 0
            share = w[rows][known].sum() / total
            if share <= 0:
                continue
            at, width, present = c[known], self.width[f], None
            if f < self.n_num:
                # only the values that the node holds: a table of them is no longer than its rows
                if width <= 4 * len(at):
                    there = np.bincount(at, minlength=width) > 0
                    present, at = np.flatnonzero(there), (np.cumsum(there) - 1)[at]
                else:
                    present, at = np.unique(at, return_inverse=True)
                width = len(present)
            table = np.bincount(at * self.n_classes + y[rows][known], w[rows][known], width * self.n_classes).reshape(-1, self.n_classes)
            option = self._threshold(table, share, total) if f < self.n_num else self._branches(table, share, total)
            if option:
                gain, ratio, cut = option
                found.append((gain, ratio, int(present[cut]) if present is not None else cut, f))
        if not found:
            return node
        _, _, cut, f = self.choose(found)
        c = codes[f][rows]
        branch = np.where(c < 0, -1, (c > cut).astype(int)) if f < self.n_num else c
        sizes = np.bincount(branch[branch >= 0], w[rows][branch >= 0])
        lost = rows[branch < 0]
        node.feature = f
        if f < self.n_num:
            node.threshold = float(self.edges[f][cut])
            node.below = float(self._num[rows, f][(c >= 0) & (c <= cut)].max())
        for b in np.flatnonzero(sizes > 0):
            own = rows[branch == b]
            if len(lost):
                part = w.copy()
                part[lost] = w[lost] * sizes[b] / sizes.sum()
                node.children[int(b)] = self._grow(codes, y, part, np.concatenate([own, lost]), depth + 1, used | ({f} if f >= self.n_num else set()))
            else:
                node.children[int(b)] = self._grow(codes, y, w, own, depth + 1, used | ({f} if f >= self.n_num else set()))
        return node

    @staticmethod
    def choose(found: list[tuple]) -> tuple:
        """Of (gain, ratio, cut, feature), the best ratio among gains that are average at least; the first feature of equals."""
        average = sum(g for g, *_ in found) / len(found)
        return max((x for x in found if x[0] >= average - 1e-9), key=lambda x: (x[1], -x[3]))

    def ends(self, counts: np.ndarray, depth: int) -> bool:
        """Whether a node of these class counts stays a leaf."""
        total = counts.sum()
        return (self.max_depth is not None and depth >= self.max_depth) or total < 2 * self.min_leaf or counts.max() >= total - 1e-9

    def _threshold(self, table, share, total):
        left = np.cumsum(table, axis=0)[:-1]
        if not len(left):
            return None
        all_ = table.sum(axis=0)
        gain, valid = self.cut_gains(left, all_)
        if not valid.any():
            return None
        at = int(gain.argmax())
        return self.scored(float(gain[at]), int(valid.sum()), left[at], all_, share, total, at)

    def cut_gains(self, left: np.ndarray, all_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Gain of each cut (-1 where a side is too small) and whether it may be one, from the class counts on its left and of all known rows."""
        right = all_ - left
        a, b = left.sum(axis=1), right.sum(axis=1)
        valid = (a >= self.min_leaf) & (b >= self.min_leaf)
        if not valid.any():
            return np.full(len(left), -1.0), valid
        gain = entropy(all_) - (a * entropy(left) + b * entropy(right)) / (a + b)
        return np.where(valid, gain, -1), valid

    @staticmethod
    def scored(gain: float, n_valid: int, left: np.ndarray, all_: np.ndarray, share: float, total: float, at):
        """(gain, ratio, at) of a feature's best cut, or None if it gains nothing after the price of the choice among n_valid cuts."""
        best = share * gain - math.log2(max(1, n_valid)) / total
        if best <= 1e-9:
            return None
        a, n = left.sum(), all_.sum()
        split = entropy(np.array([a, (all_ - left).sum(), total - n]))
        return best, best / max(split, 1e-9), at

    def _branches(self, table, share, total):
        sizes = table.sum(axis=1)
        if (sizes >= self.min_leaf).sum() < 2:
            return None
        n = sizes.sum()
        gain = share * (entropy(table.sum(axis=0)) - (sizes * np.where(sizes > 0, entropy(table), 0)).sum() / n)
        if gain <= 1e-9:
            return None
        return gain, gain / max(entropy(np.append(sizes, total - n)), 1e-9), -1

    def _bound(self, counts: np.ndarray) -> float:
        n = counts.sum()
        return n * upper_error(n - counts.max(), n, self.confidence)

    def _prune(self, node: Node) -> float:
        if not node.children:
            return self._bound(node.counts)
        below = sum(self._prune(c) for c in node.children.values())
        leaf = self._bound(node.counts)
        if leaf <= below + 0.1:
            node.children, node.feature = {}, -1
            return leaf
        return below

    def distribution(self, frame: Frame) -> np.ndarray:
        out = np.zeros((len(frame), self.n_classes))
        self._send(self.root, frame, np.arange(len(frame)), np.ones(len(frame)), out)
        return out

    def _send(self, node, frame, rows, weight, out):
        if not len(rows):
            return
        if not node.children:
            out[rows] += weight[:, None] * node.counts / max(node.counts.sum(), 1e-12)
            return
        if node.feature < self.n_num:
            x = frame.num[rows, node.feature]
            branch = np.where(np.isnan(x), -1, (x > node.threshold).astype(int))
        else:
            branch = frame.cat[rows, node.feature - self.n_num]
        total = sum(c.counts.sum() for c in node.children.values())
        lost = ~np.isin(branch, list(node.children))
        for b, child in node.children.items():
            own = branch == b
            self._send(child, frame, rows[own], weight[own], out)
            if lost.any():
                self._send(child, frame, rows[lost], weight[lost] * child.counts.sum() / total, out)

    def predict(self, frame: Frame) -> np.ndarray:
        return self.distribution(frame).argmax(axis=1)


class LevelVote:
    """A stump of one symbolic column: the heaviest class of each of its levels, the heaviest of all where a level is new.

    column: its name; None: the column of least training error, the first of equals. Equal weights go to the first class.
    """

    def __init__(self, column: str | None = None):
        self.column = column

    def fit(self, frame: Frame, y: np.ndarray, n_classes: int, weights: np.ndarray | None = None) -> "LevelVote":
        w = np.ones(len(y)) if weights is None else weights
        self.prior = int(np.bincount(y, w, n_classes).round(9).argmax())
        best = None
        for j, name in enumerate(frame.cat_names):
            if self.column in (None, name):
                code = frame.cat[:, j]
                known = code >= 0
                table = np.bincount(code[known] * n_classes + y[known], w[known], (int(code.max(initial=0)) + 1) * n_classes).reshape(-1, n_classes)
                said = table.round(9).argmax(axis=1)
                said[table.sum(axis=1) <= 0] = self.prior
                wrong = round(float(w.sum() - table[np.arange(len(table)), said].sum() - w[~known & (y == self.prior)].sum()), 9)
                if best is None or wrong < best[0]:
                    best = (wrong, name, said)
        if best is None:
            raise ValueError(f"no symbolic column {self.column or ''}".rstrip())
        _, self.chosen, self.said = best
        return self

    def predict(self, frame: Frame) -> np.ndarray:
        code = frame.cat[:, frame.cat_names.index(self.chosen)]
        known = (code >= 0) & (code < len(self.said))
        return np.where(known, self.said[np.clip(code, 0, len(self.said) - 1)], self.prior)


class AdaBoostM1:
    """Rounds of trees on reweighted rows; the weight of right rows is multiplied by e / (1 - e), a tree votes with ln((1 - e) / e)."""

    def __init__(self, rounds: int = 10, make=None, **tree):
        self.rounds, self.make, self.tree = rounds, make or C45Tree, tree

    def fit(self, frame, y, n_classes, weights=None):
        w = np.full(len(y), 1.0) if weights is None else weights.astype(float)
        total = w.sum()
        self.n_classes, self.members, self.votes, self.errors = n_classes, [], [], []
        for _ in range(self.rounds):
            w *= total / w.sum()
            member = self.make(**self.tree).fit(frame, y, n_classes, w)
            wrong = member.predict(frame) != y
            e = float((w * wrong).sum() / w.sum())
            self.errors.append(e)
            if e >= 0.5 or e <= 0:
                if not self.members or e <= 0:
                    self.members.append(member)
                    self.votes.append(math.log(1e6) if e <= 0 else 1.0)
                break
            self.members.append(member)
            self.votes.append(math.log((1 - e) / e))
            w = np.where(wrong, w, w * e / (1 - e))
        return self

    def predict(self, frame):
        total = np.zeros((len(frame), self.n_classes))
        for member, vote in zip(self.members, self.votes, strict=True):
            total[np.arange(len(frame)), member.predict(frame)] += vote
        return total.argmax(axis=1)


class Bagging:
    """Trees on Poisson(1) multiplicities of the rows, by plurality; ties go to the larger class."""

    def __init__(self, models: int = 10, seed: int = 42, **tree):
        self.models, self.seed, self.tree = models, seed, tree

    def fit(self, frame, y, n_classes, weights=None):
        w = np.ones(len(y)) if weights is None else weights
        self.prior = np.bincount(y, w, n_classes) / max(w.sum(), 1e-12)
        self.members = []
        for t in range(self.models):
            times = np.random.default_rng([self.seed, t]).poisson(1.0, len(y)) * w
            rows = np.flatnonzero(times)
            self.members.append(C45Tree(**self.tree).fit(frame.rows(rows), y[rows], n_classes, times[rows].astype(float)))
        return self

    def predict(self, frame):
        total = np.zeros((len(frame), len(self.prior)))
        for member in self.members:
            total[np.arange(len(frame)), member.predict(frame)] += 1
        return (total + 0.5 * self.prior).argmax(axis=1)


class NaiveBayes:
    """Over bins of numeric features and levels of symbolic ones, with Laplace smoothing; unknowns say nothing."""

    def __init__(self, bins: int = 10):
        self.bins = bins

    def codes(self, frame: Frame) -> list[np.ndarray]:
        return [np.where(np.isnan(frame.num[:, j]), -1, np.searchsorted(e, frame.num[:, j], "left")) for j, e in enumerate(self.edges)] + [frame.cat[:, j] for j in range(frame.cat.shape[1])]

    def fit(self, frame, y, n_classes, weights=None, edges=None):
        w = np.ones(len(y)) if weights is None else weights
        self.edges = edges or [edges_of(frame.num[:, j], self.bins) for j in range(frame.num.shape[1])]
        self.prior = np.log((np.bincount(y, w, n_classes) + 1) / (w.sum() + n_classes))
        self.tables = []
        for c in self.codes(frame):
            width = int(c.max(initial=0)) + 1
            known = c >= 0
            t = np.bincount(c[known] * n_classes + y[known], w[known], width * n_classes).reshape(width, n_classes) + 1
            self.tables.append(np.log(t / t.sum(axis=0)))
        return self

    def predict(self, frame):
        total = np.repeat(self.prior[None], len(frame), 0)
        for c, t in zip(self.codes(frame), self.tables, strict=True):
            total += np.where(((c >= 0) & (c < len(t)))[:, None], t[np.clip(c, 0, len(t) - 1)], 0)
        return total.argmax(axis=1)


class NBTree:
    """A tree whose leaves are naive Bayes: a node splits if the children's cross-validated accuracy cuts its errors by min_gain at least."""

    def __init__(self, min_rows: int = 30, min_gain: float = 0.05, folds: int = 5, bins: int = 10, max_depth: int | None = None, seed: int = 7):
        self.min_rows, self.min_gain, self.folds, self.bins, self.max_depth, self.seed = min_rows, min_gain, folds, bins, max_depth, seed

    def fit(self, frame, y, n_classes, weights=None):
        self.n_classes = n_classes
        self.fold = np.random.default_rng(self.seed).integers(0, self.folds, len(y))
        self.root = self._grow(frame, y, np.arange(len(y)), 0)
        return self

    def _utility(self, frame, y, rows) -> float:
        hits = 0
        for f in range(self.folds):
            test, train = rows[self.fold[rows] == f], rows[self.fold[rows] != f]
            if len(test) and len(train):
                hits += (NaiveBayes(self.bins).fit(frame.rows(train), y[train], self.n_classes).predict(frame.rows(test)) == y[test]).sum()
        return hits / max(1, len(rows))

    def _grow(self, frame, y, rows, depth):
        leaf = NaiveBayes(self.bins).fit(frame.rows(rows), y[rows], self.n_classes)
        if len(rows) < self.min_rows or (self.max_depth is not None and depth >= self.max_depth) or len(np.unique(y[rows])) < 2:
            return leaf
        own = self._utility(frame, y, rows)
        best = None
        n_num = frame.num.shape[1]
        for f in range(n_num + frame.cat.shape[1]):
            x = frame.num[rows, f] if f < n_num else frame.cat[rows, f - n_num]
            if f < n_num:
                cut = np.nanmedian(x) if not np.isnan(x).all() else np.nan
                branch = (x > cut).astype(int)
            else:
                cut, branch = None, x
            parts = {int(b): rows[branch == b] for b in np.unique(branch)}
            if len(parts) < 2 or len(parts) > 50:
                continue
            utility = sum(len(p) * self._utility(frame, y, p) for p in parts.values()) / len(rows)
            if best is None or utility > best[0]:
                best = (utility, f, cut, parts)
        if best is None or (best[0] - own) < self.min_gain * (1 - own):
            return leaf
        return (best[1], best[2], {b: self._grow(frame, y, p, depth + 1) for b, p in best[3].items()}, leaf)

    def predict(self, frame):
        out = np.zeros(len(frame), np.int64)

        def send(node, rows):
            if not len(rows):
                return
            if isinstance(node, NaiveBayes):
                out[rows] = node.predict(frame.rows(rows))
                return
            f, cut, children, leaf = node
            branch = (frame.num[rows, f] > cut).astype(int) if cut is not None else frame.cat[rows, f - frame.num.shape[1]]
            for b, child in children.items():
                send(child, rows[branch == b])
            send(leaf, rows[~np.isin(branch, list(children))])

        send(self.root, np.arange(len(frame)))
        return out
