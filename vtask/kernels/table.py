"""A bounded table in memory: numbers as doubles, categories as tokens; attribute kinds and the profile of a dataset."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd

MISSING = "\x00null"
NUM, CAT, CONST, DROPPED = "numerical", "categorical", "constant", "identifier"
PROFILES = ("numerical-only", "categorical-only", "mixed", "mixed-numerical-dominant", "mixed-categorical-dominant")


class NoUsableAttributes(ValueError):
    """Every attribute of the context is constant or an identifier."""


def card_threshold(n: int) -> int:
    """How many distinct values an attribute of n valid values may have and still be categorical."""
    return min(20, max(2, math.ceil(math.sqrt(n))))


def attribute_kind(n: int, u: int, int_like: bool, is_text: bool = False) -> str:
    """Kind of an attribute of n valid and u distinct values."""
    if n == 0 or u <= 1:
        return CONST
    if is_text:
        return CAT if u <= card_threshold(n) and u / n <= 0.5 else NUM if u / n <= 0.5 else DROPPED
    few = u <= card_threshold(n)
    return CAT if (u < 10 or few) and (int_like or few) and u / n <= 0.5 else NUM


def dataset_profile(kinds: list[str], dominant: float = 0.80) -> str:
    num, cat = kinds.count(NUM), kinds.count(CAT)
    if num + cat == 0:
        raise NoUsableAttributes("no attribute is numerical or categorical")
    if not cat:
        return PROFILES[0]
    if not num:
        return PROFILES[1]
    share = cat / (num + cat)
    return PROFILES[4] if share >= dominant else PROFILES[3] if 1 - share >= dominant else PROFILES[2]


@dataclass
class Frame:
    """Rows as a matrix of numbers and a matrix of tokens."""

    x: np.ndarray
    c: np.ndarray
    num: list[str] = field(default_factory=list)
    cat: list[str] = field(default_factory=list)

    @property
    def n(self) -> int:
        return max(self.x.shape[0], self.c.shape[0])

    def take(self, rows) -> Frame:
        return Frame(self.x[rows], self.c[rows], self.num, self.cat)

    def without(self, name: str) -> Frame:
        """Without one attribute."""
        if name in self.num:
            k = [i for i, a in enumerate(self.num) if a != name]
            return Frame(self.x[:, k], self.c, [self.num[i] for i in k], self.cat)
        k = [i for i, a in enumerate(self.cat) if a != name]
        return Frame(self.x, self.c[:, k], self.num, [self.cat[i] for i in k])


@dataclass
class Schema:
    """Kinds found on a context, and how to turn rows into a Frame."""

    kinds: dict[str, str]
    fill: dict[str, float]
    freq: dict[str, dict[str, float]]

    @property
    def num(self) -> list[str]:
        return [a for a, k in self.kinds.items() if k == NUM]

    @property
    def cat(self) -> list[str]:
        return [a for a, k in self.kinds.items() if k == CAT]

    @property
    def profile(self) -> str:
        return dataset_profile(list(self.kinds.values()))

    @classmethod
    def fit(cls, pdf: pd.DataFrame, attrs: list[str]) -> Schema:
        kinds, fill, freq = {}, {}, {}
        for a in attrs:
            s = pdf[a].dropna()
            text = not pd.api.types.is_numeric_dtype(s)
            u = s.nunique()
            whole = not text and bool(np.all(s.to_numpy(float) == np.floor(s.to_numpy(float))))
            kinds[a] = attribute_kind(len(s), u, whole, text)
            if kinds[a] == NUM:
                if text:  # frequent strings that are too many to be categories count by how common they are
                    freq[a] = (s.value_counts() / len(s)).to_dict()
                    fill[a] = float(np.median([freq[a][v] for v in s]))
                else:
                    fill[a] = float(np.median(s.to_numpy(float)))
        return cls(kinds, fill, freq)

    def frame(self, pdf: pd.DataFrame) -> Frame:
        def number(a):
            s = pdf[a].map(self.freq[a]).fillna(0.0) if a in self.freq else pdf[a]
            return s.astype(float).fillna(self.fill[a]).to_numpy()

        def token(a):
            s = pdf[a]
            if pd.api.types.is_numeric_dtype(s):
                return np.array([MISSING if pd.isna(v) else repr(float(v)) for v in s], object)
            return np.array([MISSING if v is None or v != v else str(v) for v in s], object)

        n = len(pdf)
        x = np.stack([number(a) for a in self.num], axis=1) if self.num else np.zeros((n, 0))
        c = np.stack([token(a) for a in self.cat], axis=1) if self.cat else np.empty((n, 0), object)
        return Frame(x, c, self.num, self.cat)
