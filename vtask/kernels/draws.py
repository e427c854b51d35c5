"""Stateless random numbers: a number is a function of seed, purpose and key, the same in Python, Spark and SQL."""

from __future__ import annotations

import hashlib

import numpy as np

SCALE = float(16**13)


def u01(seed: int, purpose: str, *keys) -> float:
    """Uniform in [0, 1): the first 13 hex digits of an md5."""
    text = "|".join(map(str, (seed, purpose, *keys)))
    return int(hashlib.md5(text.encode()).hexdigest()[:13], 16) / SCALE


def uniforms(seed: int, purpose: str, keys) -> np.ndarray:
    return np.array([u01(seed, purpose, k) for k in keys])


def normals(seed: int, purpose: str, keys) -> np.ndarray:
    """Standard normals by the Box-Muller transform of two uniforms."""
    a, b = uniforms(seed, purpose + ".a", keys), uniforms(seed, purpose + ".b", keys)
    return np.sqrt(-2 * np.log(1 - a)) * np.cos(2 * np.pi * b)


def drawn_subset(seed: int, task: str, attrs: list[str]) -> list[str]:
    """Half of the attributes, two at least, of smallest draw; in their own order."""
    attrs = list(attrs)
    if len(attrs) <= 2:
        return attrs
    size = max(2, -(-len(attrs) // 2))
    return sorted(sorted(attrs, key=lambda a: u01(seed, "subset", task, a))[:size], key=attrs.index)


def rng(seed: int, purpose: str) -> np.random.Generator:
    """A generator for bulk draws on bounded data."""
    return np.random.default_rng(int(hashlib.md5(f"{seed}|{purpose}".encode()).hexdigest()[:15], 16))
