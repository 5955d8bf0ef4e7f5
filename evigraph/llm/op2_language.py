"""Language identification by compression.

Each language gets a raw-content zstandard dictionary cut from labelled texts. Texts are put in lower case
and all but letters becomes single spaces; then a text is cut into windows of WINDOW bytes (all of it, no
prefix; a text under SHORT bytes is repeated up to that length, or no dictionary could show a gain). Each window
is compressed with every dictionary, and the language with the smallest total wins. ``score`` is the share of the runner-up's bytes
that the winner saves, mapped to (0, 1]; a text whose saving is under MARGIN is marked ``rejected``.

Fitting reads labelled rows only: for each language the FIT_ROWS rows that come first by a hash of their
id, each cut to FIT_BYTES (both bounds are parameters, so the model's size is bounded whatever the corpus).

Defined cases: null text or no letter gives ``und`` with score 0, rejected; no labelled row gives ``und`` for all;
ties go to the language that sorts first; extra columns stay; repeated rows are kept, each with its own result.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import pandas as pd
import regex
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.llm.common import documents

FIT_ROWS, FIT_BYTES, DICT_BYTES = 96, 2_048, 64 * 1024
WINDOW, SHORT, LEVEL, MARGIN = 2_048, 96, 7, 0.002


def fit(labelled: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang") -> dict[str, bytes]:
    """One dictionary for each language. What is collected is at most FIT_ROWS * FIT_BYTES a language."""
    order = Window.partitionBy("l").orderBy("h", "k")
    chosen = (
        labelled.where(F.col(lang).isNotNull() & F.col(text).isNotNull())
        .select(F.col(lang).alias("l"), F.crc32(F.col(key).cast("string").cast("binary")).alias("h"), F.substring(text, 1, FIT_BYTES).alias("t"), F.col(key).alias("k"))
        .where(F.length("t") > 20)
        .withColumn("r", F.row_number().over(order))
        .where(F.col("r") <= FIT_ROWS)
    )
    pieces: dict[str, list[bytes]] = {}
    for row in sorted(chosen.select("l", "r", "t").collect(), key=lambda x: (x["l"], -x["r"])):
        pieces.setdefault(row["l"], []).append(plain(row["t"]))
    # What stands last in a raw dictionary is cheapest to refer to and is kept when it is full.
    return {k: b" ".join(v)[-DICT_BYTES:] for k, v in pieces.items()}


@functools.lru_cache(maxsize=2)
def _compressors(model: tuple[tuple[str, bytes], ...]) -> list[tuple[str, zstandard.ZstdCompressor]]:
    out = []
    for name, raw in model:
        d = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        how = zstandard.ZstdCompressionParameters.from_level(LEVEL, min_match=3, dict_size=len(raw), source_size=WINDOW, write_content_size=False, write_checksum=False, write_dict_id=False)
        d.precompute_compress(compression_params=how)
        out.append((name, zstandard.ZstdCompressor(dict_data=d, compression_params=how)))
    return out


_OTHER = regex.compile(r"[^\p{L}]+")


def plain(text: str) -> bytes:
    return f" {_OTHER.sub(' ', text.lower())} ".encode("utf-8", "replace")


def classify(text: str | None, model: tuple[tuple[str, bytes], ...]) -> tuple[str, float, bool]:
    if text is None or not model or not (raw := plain(text)).strip():
        return "und", 0.0, True
    if len(raw) < SHORT:
        raw *= -(-SHORT // len(raw))
    windows = [raw[i : i + WINDOW] for i in range(0, len(raw), WINDOW)]
    sizes = sorted((sum(len(c.compress(w)) for w in windows), name) for name, c in _compressors(model))
    if len(sizes) == 1:
        return sizes[0][1], 1.0, False
    saving = 1 - sizes[0][0] / max(1, sizes[1][0])
    return sizes[0][1], 0.5 + 0.5 * min(1.0, saving * 4), saving < MARGIN


def identify(df: DataFrame, model: dict[str, bytes], text: str = "text") -> DataFrame:
    """Adds lang_pred, score and rejected; the bounded model travels with the tasks."""
    fixed = tuple(sorted(model.items()))
    shared = df.sparkSession.sparkContext.broadcast(fixed)

    @F.pandas_udf("lang_pred string, score double, rejected boolean")
    def predict(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        own = shared.value
        for texts in batches:
            yield pd.DataFrame([classify(t, own) for t in texts], columns=["lang_pred", "score", "rejected"])

    return df.withColumn("_p", predict(F.col(text))).select(*[F.col(f"`{c}`") for c in df.columns if c not in ("lang_pred", "score", "rejected")], "_p.*")


def held_out(key: str = "doc_id"):
    return F.crc32(F.col(key).cast("string").cast("binary")) % 5 == 0


def op2_language_zstd(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every text, learned only from rows that aren't held out."""
    docs = documents(spark, sf_dir)
    model = fit(docs.where(~F.coalesce(held_out(), F.lit(True))))
    return identify(docs.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "text"), model).drop("text")


QUERIES = {"op2_language_zstd": op2_language_zstd}
