"""Hashes of the words of many texts at once: runs of code points between others, by prefix sums of a polynomial."""

from __future__ import annotations

import functools

import numpy as np

_BASE = 0x100000001B3


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def powers(n: int, base: int) -> np.ndarray:
    return np.cumprod(np.r_[np.uint64(1), np.full(max(n - 1, 0), base, dtype=np.uint64)])


@functools.cache
def _kept_powers(base: int) -> np.ndarray:
    return powers(1 << 18, base)


def _powers(n: int, base: int) -> np.ndarray:
    return _kept_powers(base)[:n] if n <= 1 << 18 else powers(n, base)


@functools.cache
def letters() -> np.ndarray:
    """For every code point whether it is a letter or a digit."""
    return np.fromiter((chr(i).isalnum() for i in range(0x110000)), bool, 0x110000)


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


def word_hashes(points: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, hash) of the maximal runs of points that are inside a word.

    The polynomial sum up to the end of a word, less that up to its start, is the sum over the word times a power of
    the base, which an odd base lets one divide out.
    """
    edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    if len(inside) and inside[0]:
        edge = np.r_[0, edge]
    if len(edge) % 2:
        edge = np.r_[edge, len(points)]
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return start, end, np.zeros(0, dtype=np.uint64)
    total = np.cumsum((points.astype(np.uint64) + np.uint64(1)) * _powers(len(points), _BASE), dtype=np.uint64)
    before = np.where(start > 0, total[start - 1], np.uint64(0))
    return start, end, mixed((total[end - 1] - before) * _powers(int(start[-1]) + 1, pow(_BASE, -1, 1 << 64))[start])
