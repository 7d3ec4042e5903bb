"""Exact edit distance for texts of any length: trimmed, settled by counts of characters where these bound it from both
sides, else bit-parallel over Python integers, in Arrow batches; many pairs of few edits together."""

from __future__ import annotations

import functools
import operator
from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def trimmed(a: str, b: str) -> tuple[str, str]:
    """Both texts without their common begin and end, which never cost an edit."""
    n = min(len(a), len(b))
    low = _common(a, b, n)
    high = _common(a[low:][::-1], b[low:][::-1], n - low)
    return a[low : len(a) - high], b[low : len(b) - high]


def _common(a: str, b: str, most: int) -> int:
    """Length of the common begin, at most ``most``, by halving."""
    low, high = 0, most
    while low < high:
        middle = (low + high + 1) // 2
        if a[low:middle] == b[low:middle]:
            low = middle
        else:
            high = middle - 1
    return low


def edit_distance(a: str, b: str, most: int | None = None) -> int:
    """Levenshtein distance in code points; time O(len(a) * len(b) / word size). With ``most`` it stops once the
    distance must be greater and returns most + 1."""
    return _middle_distance(*trimmed(a, b), most)


def _middle_distance(a: str, b: str, most: int | None) -> int:
    if not a or not b:
        return len(a) + len(b)
    if len(a) > len(b):
        a, b = b, a
    limit = len(b) if most is None else most
    if len(b) - len(a) > limit:
        return limit + 1
    # characters that one text has more often than the other cost an edit each
    more, less = Counter(a), Counter(b)
    least = max((more - less).total(), (less - more).total())
    if least > limit:
        return limit + 1
    if len(a) == len(b) and sum(map(operator.ne, a, b)) == least:
        return least  # changing each place where they differ takes no more
    where: dict[str, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i
    full, top = (1 << len(a)) - 1, 1 << (len(a) - 1)
    plus, minus, distance, left = full, 0, len(a), len(b)
    for c in b:
        match = where.get(c, 0)
        diagonal = (((match & plus) + plus) ^ plus) | match | minus
        up, down = minus | (~(diagonal | plus) & full), plus & diagonal
        if up & top:
            distance += 1
        elif down & top:
            distance -= 1
        left -= 1
        if distance - left > limit:  # every character left saves one at most
            return limit + 1
        up, down = ((up << 1) | 1) & full, (down << 1) & full
        plus, minus = down | (~(diagonal | up) & full), up & diagonal
    return distance


def edit_distances(pairs: list[tuple[str, str]], most: list[int], chars: int = 2_000_000) -> list[int]:
    """``edit_distance`` of many pairs at once, each with its ``most``: edit by edit, over all pairs and diagonals of a
    batch of about ``chars`` characters together. Pairs of many edits or of many different characters go one by one."""
    out: list[int] = [0] * len(pairs)
    waiting, size = [], 0
    for i, (a, b) in enumerate(pairs):
        a, b = trimmed(a, b)
        longer = max(len(a), len(b))
        codes = None
        if min(len(a), len(b)) > 32:
            codes = np.frombuffer((a + b).encode("utf-32-le", "surrogatepass"), np.uint32)
            known, codes = np.unique(codes, return_inverse=True)
            counted = np.bincount(codes[: len(a)], minlength=len(known)) - np.bincount(codes[len(a) :], minlength=len(known))
            if len(known) > 250 or max(counted[counted > 0].sum(), -counted[counted < 0].sum()) > 64 + longer // 8:
                codes = None
        if codes is None:
            out[i] = _middle_distance(a, b, most[i])
            continue
        waiting.append((i, codes[: len(a)].astype(np.uint8), codes[len(a) :].astype(np.uint8), min(most[i], 64 + longer // 8)))
        size += len(a) + len(b)
        if size > chars:
            _by_waves(waiting, pairs, most, out)
            waiting, size = [], 0
    if waiting:
        _by_waves(waiting, pairs, most, out)
    return out


def _equal_bytes(differ: np.ndarray) -> np.ndarray:
    """How many of the lowest bytes are zero, 8 of a zero."""
    return (np.bitwise_count(~differ & (differ - np.uint64(1))) >> 3).astype(np.int32)


def _by_waves(waiting: list, pairs: list[tuple[str, str]], most: list[int], out: list[int]) -> None:
    """Per diagonal the furthest place that d edits reach, for all waiting pairs, d rising."""
    place, flat, at = [], [], 0
    for i, x, y, _ in waiting:
        place.append((at, at + len(x) + 1, len(x), len(y)))
        flat += [x, np.array([251], np.uint8), y, np.array([252], np.uint8)]  # ends that match nothing
        at += len(x) + len(y) + 2
    flat = np.concatenate([*flat, np.zeros(8, np.uint8)])
    # the eight characters from each place on
    eight = np.zeros(at, np.uint64)
    for k in range(8):
        eight |= flat[k : k + at].astype(np.uint64) << np.uint64(8 * k)
    row = np.arange(len(waiting))
    begin_x, begin_y, n, m = np.ascontiguousarray(np.array(place, np.int32).T)
    cap = np.array([w[3] for w in waiting])
    reach, d = np.zeros((len(row), 1), np.int32), 0
    while len(row):
        if d:
            last = np.full((len(row), 2 * d + 3), -(1 << 28), np.int32)
            last[:, 2:-2] = reach
            reach = np.maximum(np.maximum(last[:, 1:-1], last[:, 2:]) + 1, last[:, :-2])
        diagonal = np.arange(-d, d + 1, dtype=np.int32)
        reach = np.minimum(np.minimum(reach, n[:, None]), m[:, None] - diagonal)
        live = (reach >= 0) & (reach + diagonal >= 0)
        i = np.where(live, begin_x[:, None] + reach, 0).ravel()  # place 0 and the end of all match in no character
        j = np.where(live, begin_y[:, None] + diagonal + reach, at - 1).ravel()
        differ = eight[i] ^ eight[j]
        grown = _equal_bytes(differ)
        left = np.flatnonzero(differ == 0)
        i, j = i[left], j[left]
        while len(left):
            i, j = i + 8, j + 8
            differ = eight[i] ^ eight[j]
            grown[left] += _equal_bytes(differ)
            same = differ == 0
            left, i, j = left[same], i[same], j[same]
        reach += grown.reshape(reach.shape)
        reach[~live] = -(1 << 28)
        target = m - n + d
        met = np.zeros(len(row), bool)
        inside = np.flatnonzero((target >= 0) & (target <= 2 * d))
        met[inside] = reach[inside, target[inside]] >= n[inside]
        for r in row[met]:
            out[waiting[r][0]] = d
        over = ~met & (d >= cap)
        for r in row[over]:
            i = waiting[r][0]
            out[i] = edit_distance(*pairs[i], most[i]) if d < most[i] else most[i] + 1
        stay = ~met & ~over
        if not stay.all():
            row, begin_x, begin_y, n, m, cap, reach = row[stay], begin_x[stay], begin_y[stay], n[stay], m[stay], cap[stay], reach[stay]
        d += 1


@functools.lru_cache(maxsize=64)
def _remembered(a: str, b: str, most: int) -> int:
    """Versions of one text often differ in the same middle."""
    return _middle_distance(a, b, most)


def long_edit_similarity(a: Column | str, b: Column | str, floor: float = 0.0) -> Column:
    """As edit_similarity, for texts of any length; below ``floor`` the value is some number below it."""

    @F.pandas_udf(T.DoubleType())
    def similarity(a: pd.Series, b: pd.Series) -> pd.Series:
        out = []
        for x, y in zip(a, b, strict=True):
            longer = 0 if x is None or y is None else max(len(x), len(y))
            if x is None or y is None:
                out.append(None)
            elif not longer:
                out.append(1.0)
            else:
                out.append(1 - _remembered(*trimmed(x, y), int((1 - floor) * longer) + 1) / longer)
        return pd.Series(out, dtype="float64")

    return similarity(a, b)
