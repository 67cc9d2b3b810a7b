"""The arrays that learners see: numeric columns (unknown: NaN) and symbolic codes (unknown: negative)."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Frame:
    num: np.ndarray
    cat: np.ndarray
    num_names: list[str]
    cat_names: list[str]

    def rows(self, at: np.ndarray) -> "Frame":
        return Frame(self.num[at], self.cat[at], self.num_names, self.cat_names)

    def only(self, names: list[str]) -> "Frame":
        a = [i for i, n in enumerate(self.num_names) if n in names]
        b = [i for i, n in enumerate(self.cat_names) if n in names]
        return Frame(self.num[:, a], self.cat[:, b], [self.num_names[i] for i in a], [self.cat_names[i] for i in b])

    def beside(self, other: "Frame") -> "Frame":
        return Frame(np.concatenate([self.num, other.num], axis=1), np.concatenate([self.cat, other.cat], axis=1), self.num_names + other.num_names, self.cat_names + other.cat_names)

    def __len__(self) -> int:
        return len(self.num)


def edges_of(values: np.ndarray, bins: int | None) -> np.ndarray:
    """Ascending cut points: midpoints of neighbouring values, or quantiles where there are more than `bins` values (None: never)."""
    values = values[~np.isnan(values)]
    distinct = np.unique(values)
    if bins is None or len(distinct) <= bins:
        return (distinct[1:] + distinct[:-1]) / 2
    return np.unique(np.quantile(values, np.linspace(0, 1, bins + 1)[1:-1]))


def entropy(counts: np.ndarray, axis: int = -1) -> np.ndarray:
    """Base-2 entropy of the counts along an axis."""
    total = counts.sum(axis=axis, keepdims=True)
    with np.errstate(divide="ignore", invalid="ignore"):
        p = counts / total
        return np.where(p > 0, -p * np.log2(p), 0).sum(axis=axis)
