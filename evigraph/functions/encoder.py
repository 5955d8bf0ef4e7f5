"""Text encoders: a deterministic hashed one for offline use, and the interface of a served model."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class HashEncoder:
    """Signed feature hashing of words and character trigrams, square-root counts, unit length."""

    def __init__(self, dim: int = 64):
        self.dim = dim
        self.seen: dict[str, tuple[np.ndarray, np.ndarray]] = {}

    def _features(self, word: str) -> tuple[np.ndarray, np.ndarray]:
        if word not in self.seen:
            if len(self.seen) > 200_000:
                self.seen.clear()
            grams = [(word, 2.0), *((f"#{word}#"[i : i + 3], 1.0) for i in range(len(word)))]
            h = [(zlib.crc32(g.encode()), w) for g, w in grams]
            self.seen[word] = (np.array([x % self.dim for x, _ in h]), np.array([w if x >> 31 else -w for x, w in h]))
        return self.seen[word]

    def one(self, text: str | None) -> np.ndarray:
        v = np.zeros(self.dim)
        for w in (text or "").lower().split():
            at, x = self._features(w)
            np.add.at(v, at, x)
        v = np.sign(v) * np.sqrt(np.abs(v))
        n = np.linalg.norm(v)
        return (v / n if n else v).astype(np.float32)


    def many(self, texts: Iterable[str | None]) -> np.ndarray:
        """A row for each text, with the features of all texts added up at once."""
        words = [(t or "").lower().split() for t in texts]
        code: dict[str, int] = {}
        each = np.array([code.setdefault(w, len(code)) for own in words for w in own], np.int64)
        if not len(each):
            return np.zeros((len(words), self.dim), np.float32)
        known = [self._features(w) for w in code]
        size = np.array([len(at) for at, _ in known])
        at, x = (np.concatenate([f[i] for f in known]) for i in (0, 1))
        n = size[each]
        place = np.repeat((np.cumsum(size) - size)[each] - np.cumsum(n) + n, n) + np.arange(n.sum())
        row = np.repeat(np.repeat(np.arange(len(words)), [len(own) for own in words]), n)
        v = np.bincount(row * self.dim + at[place], weights=x[place], minlength=len(words) * self.dim).reshape(-1, self.dim)
        v = np.sign(v) * np.sqrt(np.abs(v))
        norm = np.linalg.norm(v, axis=1, keepdims=True)
        return (v / np.where(norm > 0, norm, 1.0)).astype(np.float32)


#: Texts whose features are added up at once.
TEXTS = 1000


def encode(df: DataFrame, text: str, dim: int = 64, out: str = "vec", make: Callable[[], HashEncoder] | None = None) -> DataFrame:
    """Adds a unit vector. The model is made once a worker and batch iterator; a served model fits the same interface."""
    build = make or (lambda: HashEncoder(dim))

    @F.pandas_udf("array<float>")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = build()
        for texts in batches:
            parts = [model.many(texts.iloc[at : at + TEXTS]) for at in range(0, len(texts), TEXTS)]
            yield pd.Series([v for part in parts for v in part])

    return df.withColumn(out, run(F.col(text)))
