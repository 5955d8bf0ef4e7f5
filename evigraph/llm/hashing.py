"""Vectorised 64-bit hashes of words, word shingles and character shingles.

A span's hash is the difference of two prefix sums of a polynomial over random code-point
values modulo 2**64, moved to position 0, then mixed. A text is handled in slices cut between
words, so memory is bounded by the slice and the list of word hashes.
"""

from __future__ import annotations

import functools

import numpy as np

U = np.uint64
SLICE = 1 << 19
_BASE = 0x9E3779B97F4A7C15 | 1
_STEP = 0xD1342543DE82EF95 | 1


def mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64 (fixed constants)."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


@functools.cache
def _powers(size: int, base: int) -> tuple[np.ndarray, np.ndarray]:
    def run(b: int) -> np.ndarray:
        a = np.full(size, b, U)
        a[0] = 1
        return np.cumprod(a, dtype=U)

    return run(base), run(pow(base, -1, 1 << 64))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    return _powers(1 << max(16, int(n).bit_length()), _BASE)


@functools.cache
def code_values() -> np.ndarray:
    """Random value of each code point."""
    return mix(np.arange(0x110000, dtype=U) + U(0x632BE59BD9B4E019))


@functools.cache
def _tables() -> tuple[np.ndarray, np.ndarray]:
    """Random value and letter-or-digit flag of each code point."""
    n = 0x110000
    return code_values(), np.fromiter((chr(i).isalnum() for i in range(n)), bool, n)


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")


def prefix(values: np.ndarray) -> np.ndarray:
    out = np.zeros(len(values) + 1, U)
    np.cumsum(values * powers(len(values))[0][: len(values)], out=out[1:])
    return out


def spans(pre: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return mix((pre[end] - pre[start]) * powers(len(pre))[1][start])


def runs(values: np.ndarray, k: int) -> np.ndarray:
    """The polynomial over each run of k values, moved to position 0: what `spans` mixes, by doubling instead of prefix sums."""
    n, base = len(values) - k + 1, powers(k)[0]
    power, size, out, done = values, 1, None, 0
    while done < k:
        if k & size:
            out = power[:n] if out is None else out + power[done : done + n] * base[done]
            done += size
        if done < k:
            power = power[:-size] + power[size:] * base[size]
            size *= 2
    return out


def slices(text: str):
    """Pieces of at most about SLICE characters that end between words where they can."""
    at = 0
    while len(text) - at > SLICE:
        cut = text.rfind(" ", at + SLICE // 2, at + SLICE) + 1 or at + SLICE
        yield text[at:cut]
        at = cut
    yield text[at:] if at else text


def word_hashes(text: str) -> np.ndarray:
    """Hashes of the words (runs of letters and digits, lower case) in order."""
    value, inside = _tables()
    out = []
    for piece in slices(text):
        cp = code_points(piece.lower())
        flags = np.zeros(len(cp) + 2, np.int8)
        flags[1:-1] = inside[cp]
        turn = np.flatnonzero(np.diff(flags))
        if len(turn):
            out.append(spans(prefix(value[cp]), turn[::2], turn[1::2]))
    return np.concatenate(out) if out else np.zeros(0, U)


def shingles(words: np.ndarray, k: int = 5) -> np.ndarray:
    """One hash for each run of k words; a shorter text is one shingle, an empty one none."""
    n = len(words)
    if n == 0:
        return words
    step = pow(_STEP, 1, 1 << 64)
    acc = np.zeros(max(1, n - k + 1), U)
    p = 1
    for i in range(min(k, n)):
        acc += words[i : i + len(acc)] * U(p)
        p = p * step % (1 << 64)
    return mix(acc)


def char_shingles(text: str, k: int) -> np.ndarray:
    """One hash for each run of k characters; a shorter text is one shingle."""
    value = code_values()
    cp = code_points(text)
    if len(cp) <= k:
        return spans(prefix(value[cp]), np.array([0]), np.array([len(cp)])) if len(cp) else np.zeros(0, U)
    return mix(runs(value[cp], k))
