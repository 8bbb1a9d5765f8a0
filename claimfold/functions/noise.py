"""Seeded integer noise that any SQL engine computes alike: BIGINT +, * and % only.

Squares between the linear steps keep sources, attributes and seeds independent;
all products stay below 2 ** 63.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def mix_sql(k: str, s: str | int, j: str | int, salt: str | int = 0) -> str:
    """SQL text of a pseudo-random integer below 2 ** 31 - 1."""
    a = f"((({k}) * 7919 + ({s}) * 104729 + ({j}) * 1299709 + ({salt}) * 15485863) % 1000003)"
    b = f"(({a} * {a} + ({k}) * 31 + ({s}) * 17 + ({j}) * 101) % 999983)"
    return f"((({b} * {b} + {a} * 7 + 13) % 998244353) * 48271 % 2147483647)"


def mix(k: str, s: str | int, j: str | int, salt: str | int = 0) -> Column:
    return F.expr(mix_sql(f"CAST({k} AS BIGINT)", s, j, salt))


def mix_numbers(k: np.ndarray, s: int, j: int, salt: int = 0) -> np.ndarray:
    """The same integers for an array of k >= 0."""
    a = (k * 7919 + (s * 104729 + j * 1299709 + salt * 15485863)) % 1000003
    b = (a * a + k * 31 + (s * 17 + j * 101)) % 999983
    return (b * b + a * 7 + 13) % 998244353 * 48271 % 2147483647


def roll(k: str, s: str | int, j: str | int, salt: str | int = 0) -> Column:
    """Per mille: 0 to 999."""
    return mix(k, s, j, salt) % 1000
