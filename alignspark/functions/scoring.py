"""Scoring schemes: match, mismatch and linear gap, or a matrix of symbol pairs."""

from __future__ import annotations

import warnings
from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class Scoring:
    match: float = 3
    mismatch: float = 0
    gap: float = -1
    pairs: tuple[tuple[str, str, float], ...] = field(default=())

    @classmethod
    def worked_example(cls) -> Scoring:
        return cls(3, 1, -1)

    @classmethod
    def experiment(cls) -> Scoring:
        return cls(3, 0, -1)

    @classmethod
    def unit_edit(cls) -> Scoring:
        return cls(0, -1, -1)

    @classmethod
    def matrix(cls, pairs: dict[tuple[str, str], float], gap: float, match: float = 0, mismatch: float = -1) -> Scoring:
        """Scores of symbol pairs (taken both ways round); pairs not named score match or mismatch."""
        return cls(match, mismatch, gap, tuple((a, b, s) for (a, b), s in sorted(pairs.items())))

    def validate(self) -> Scoring:
        """Error for schemes in which no alignment makes sense; a warning where no mismatch would ever be used."""
        if self.match <= self.mismatch:
            raise ValueError("match must score above mismatch")
        if self.gap > 0 or self.gap == 0 and self.match <= 0:
            raise ValueError("a gap must cost")
        if self.mismatch < 2 * self.gap:
            warnings.warn("mismatch scores below two gaps, so it is never used", stacklevel=2)
        return self

    @property
    def is_whole(self) -> bool:
        return all(float(x).is_integer() for x in (self.match, self.mismatch, self.gap, *(s for _, _, s in self.pairs)))

    def table(self, symbols: list[str]) -> np.ndarray:
        """Scores of symbols by symbols; the gap symbol against itself is 0, against a letter a gap."""
        n = len(symbols)
        t = np.full((n, n), self.mismatch, float)
        np.fill_diagonal(t, self.match)
        at = {s: i for i, s in enumerate(symbols)}
        for a, b, s in self.pairs:
            if a in at and b in at:
                t[at[a], at[b]] = t[at[b], at[a]] = s
        if "_" in at:
            t[at["_"], :] = t[:, at["_"]] = self.gap
            t[at["_"], at["_"]] = 0
        return t.astype(np.int64) if self.is_whole else t
