"""The counter-based draws of `math.u01` for whole arrays of whole numbers: MD5 over columns of digits."""

from __future__ import annotations

import hashlib
import os
import threading
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

import numpy as np

_TURN = [[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]]
_K = [int(abs(np.sin(k + 1)) * 2**32) for k in range(64)]
_WORD = [k if k < 16 else (5 * k + 1) % 16 if k < 32 else (3 * k + 5) % 16 if k < 48 else 7 * k % 16 for k in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Messages that are hashed side by side: so many that two threads seldom wait for each other's Python; fewer than FEW go one by one, which is quicker.
RUN, FEW = 1 << 17, 400
#: Threads that share parts of large arrays, from so many rows on; results do not depend on them.
THREADS, SHARED = 2, 1 << 18
_POOLS: dict[int, ThreadPoolExecutor] = {}
_OWN = threading.local()


def side_by_side(f: Callable, parts: list, rows: int) -> list:
    """f of each part, in order, on THREADS threads where the parts have SHARED rows together; what f brings here stays on its thread."""
    if THREADS < 2 or len(parts) < 2 or rows < SHARED or getattr(_OWN, "shares", False):
        return [f(x) for x in parts]
    if os.getpid() not in _POOLS:  # a process that was forked has the parent's pool, but not its threads
        _POOLS.clear()
        _POOLS[os.getpid()] = ThreadPoolExecutor(THREADS, initializer=lambda: setattr(_OWN, "shares", True))
    return list(_POOLS[os.getpid()].map(f, parts))


@contextmanager
def one_thread():
    """What the calling thread brings to side_by_side stays on it."""
    was, _OWN.shares = getattr(_OWN, "shares", False), True
    try:
        yield
    finally:
        _OWN.shares = was


def strings(seed: int, phase: str, it: int, idents, k: object = 0) -> np.ndarray:
    """Draws for idents as strings, one after another."""
    md5, head, tail = hashlib.md5, f"{seed}|{phase}|{it}|", f"|{k}"
    return np.fromiter((int(md5(f"{head}{x}{tail}".encode()).hexdigest()[:13], 16) for x in idents), np.float64) / 4503599627370496.0


def numbers(seed: int, phase: str, it: int, x: np.ndarray, y: np.ndarray | None = None, k: object = 0) -> np.ndarray:
    """Draws for the idents x, or x:y, of whole numbers; equal to those of the same strings."""
    x = np.asarray(x, np.int64)
    y = None if y is None else np.asarray(y, np.int64)
    name = lambda at: map(str, x[at].tolist()) if y is None else (f"{a}:{b}" for a, b in zip(x[at].tolist(), y[at].tolist(), strict=True))
    head, tail = f"{seed}|{phase}|{it}|".encode(), f"|{k}".encode()
    width = _digits(x) * 32 + (0 if y is None else _digits(y))
    out, runs = np.empty(len(x)), []
    for form in np.flatnonzero(np.bincount(width)).tolist():
        at = np.flatnonzero(width == form)
        dx, dy = divmod(form, 32)
        if len(at) < FEW or dx == 31 or dy == 31 or len(head) + dx + (0 if y is None else 1 + dy) + len(tail) > 55:
            out[at] = strings(seed, phase, it, name(at), k)  # few, below zero, or more than one block of MD5
            continue
        runs += [(at[low : low + RUN], dx, dy) for low in range(0, len(at), RUN)]

    def run(part: tuple) -> None:
        some, dx, dy = part
        parts = [head, (x[some], dx)] + ([] if y is None else [b":", (y[some], dy)]) + [tail]
        a, b = _md5(_words(parts, len(some)), len(some))
        a, b = a.byteswap().astype(np.int64), b.byteswap().astype(np.int64)
        out[some] = ((a << 20) | (b >> 12)) / 4503599627370496.0

    side_by_side(run, runs, len(x))
    return out


def _digits(x: np.ndarray) -> np.ndarray:
    """The number of decimal digits, 31 below zero."""
    top = int(x.max()) if len(x) else 0
    out, bound = np.ones(len(x), np.int64), 10
    while bound <= top:
        out += x >= bound
        bound *= 10
    return np.where(x < 0, 31, out)


def _words(parts: list, n: int) -> list:
    """The 16 words of the padded messages: a number where all share it, else an array."""
    fixed, varied, at = [0] * 16, {}, 0
    for part in parts:
        if isinstance(part, bytes):
            for c in part:
                fixed[at // 4] |= c << 8 * (at % 4)
                at += 1
            continue
        rest, digits = part
        rest = rest.astype(np.uint32) if digits < 10 else rest.astype(np.uint64)
        for place in range(at + digits - 1, at - 1, -1):
            high = rest // rest.dtype.type(10)
            digit = (rest - high * rest.dtype.type(10)).astype(np.uint32)
            digit += np.uint32(48)
            digit <<= np.uint32(8 * (place % 4))
            word = place // 4
            varied[word] = digit if word not in varied else varied[word] | digit
            rest = high
        at += digits
    fixed[at // 4] |= 0x80 << 8 * (at % 4)
    fixed[14] = 8 * at
    return [varied[k] | np.uint32(fixed[k]) if k in varied else fixed[k] for k in range(16)]


def _md5(words: list, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the digests."""
    a, b, c, d = (np.full(n, v, np.uint32) for v in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for k in range(64):
        if k < 16:  # d ^ (b & (c ^ d))
            np.bitwise_xor(c, d, f)
            np.bitwise_and(f, b, f)
            np.bitwise_xor(f, d, f)
        elif k < 32:  # c ^ (d & (b ^ c))
            np.bitwise_xor(b, c, f)
            np.bitwise_and(f, d, f)
            np.bitwise_xor(f, c, f)
        elif k < 48:
            np.bitwise_xor(b, c, f)
            np.bitwise_xor(f, d, f)
        else:
            np.invert(d, f)
            np.bitwise_or(f, b, f)
            np.bitwise_xor(f, c, f)
        np.add(f, a, f)
        word = words[_WORD[k]]
        if isinstance(word, int):
            np.add(f, np.uint32((_K[k] + word) & 0xFFFFFFFF), f)
        else:
            np.add(f, word, f)
            np.add(f, np.uint32(_K[k]), f)
        turn = _TURN[k // 16][k % 4]
        np.left_shift(f, np.uint32(turn), t)
        np.right_shift(f, np.uint32(32 - turn), f)
        np.bitwise_or(f, t, f)
        np.add(f, b, f)
        a, d, c, b, f = d, c, b, f, a
    return a + np.uint32(_START[0]), b + np.uint32(_START[1])
