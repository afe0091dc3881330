"""Quality: how much better a text compresses with a dictionary of good text than with one of bad text."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fold_of, table, text_blocks
from .toxicity import labelled_texts, score

#: Bound on the labelled rows that the dictionaries and the calibration are fitted on, for each label.
TRAIN_ROWS_PER_LABEL = 2_500
#: Bound on the bytes of their texts.
TRAIN_BYTES = 128 << 20
DICTIONARY_BYTES, LEVEL = 1 << 16, 3
#: Texts are compressed in blocks, whole, so that the dictionary counts in the last block as in the first.
PIECE_BYTES = 4096
THRESHOLD = 0.3


def pieces(text: bytes) -> list[bytes]:
    return [text[i : i + PIECE_BYTES] for i in range(0, len(text), PIECE_BYTES)]


@dataclass
class CompressionModel:
    good: bytes
    bad: bytes
    slope: float = 1.0
    shift: float = 0.0

    def _compressors(self):
        if not hasattr(self, "_pair"):
            self._pair = []
            for raw in (self.good, self.bad):
                words = zstandard.ZstdCompressionDict(raw)
                words.precompute_compress(level=LEVEL)
                self._pair.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=words, write_content_size=False, write_checksum=False, write_dict_id=False).compress)
        return self._pair

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_pair"}

    def differences(self, texts: list[bytes]) -> np.ndarray:
        """Bytes saved by the good dictionary against the bad one, for each byte of text; 0 for an empty text."""
        if not self.good:
            return np.zeros(len(texts))
        good, bad = self._compressors()
        return np.array([sum(len(bad(p)) - len(good(p)) for p in pieces(t)) / max(1, len(t)) for t in texts], float)

    def scores(self, texts: list[bytes]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.differences(texts) + self.shift, -500, 500)))


def _train_dictionary(texts: list[bytes]) -> bytes:
    samples = [p for t in texts for p in pieces(t)]
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
    except zstandard.ZstdError:  # too little text to find repeats in: the text itself is the dictionary
        return b"".join(samples)[-DICTIONARY_BYTES:]


def platt(x: np.ndarray, y: np.ndarray, rounds: int = 100) -> tuple[float, float]:
    """Slope and shift of the logistic curve through (x, y), by Newton steps with a weak ridge; both 0 without points."""
    scale = (x.std() if len(x) else 0.0) or 1.0
    v = np.stack([x / scale, np.ones_like(x)], 1)
    w = np.zeros(2)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(v @ w, -30, 30)))
        step = np.linalg.solve((v * (p * (1 - p))[:, None]).T @ v + 1e-3 * np.eye(2), v.T @ (y - p) - 1e-3 * w)
        w += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return float(w[0] / scale), float(w[1])


def fit(
    docs: DataFrame, labels: DataFrame, label: str = "quality", key: str = "doc_id", text: str = "text", rows: int = TRAIN_ROWS_PER_LABEL, most: int = TRAIN_BYTES
) -> CompressionModel:
    """Of each label's share of a bounded sample two thirds make the dictionary and one third the calibration, weighed back to the labels' own shares.

    Null labels and labels other than 0 and 1 are left out, as are labels whose document is absent; a null text counts as empty; a
    repeated row counts as often as it is there. Without documents of both labels for dictionary and calibration the score is one
    half for every text.
    """
    shares = {r["y"]: r["n"] for r in labels.where(F.col(label).isin(0, 1)).groupBy(F.col(label).cast("int").alias("y")).agg(F.count(F.lit(1)).alias("n")).collect()}
    got = labelled_texts(docs, labels, label, key, text, rows, most).select("y", F.col("t").cast("binary").alias("t"), "h").toArrow().sort_by([("h", "ascending"), ("y", "ascending")])
    y, texts = np.asarray(got["y"]), got["t"].to_pylist()
    held = np.zeros(len(y), bool)
    for c in (0, 1):
        held[np.flatnonzero(y == c)[::3]] = True
    if not all(((y == c) & part).any() for c in (0, 1) for part in (held, ~held)):
        return CompressionModel(b"", b"")
    model = CompressionModel(*(_train_dictionary([t for t, own in zip(texts, (y == c) & ~held, strict=True) if own]) for c in (1, 0)))
    if not (model.good and model.bad):  # no text at all in one of them
        return CompressionModel(b"", b"")
    model.slope, model.shift = platt(model.differences([t for t, h in zip(texts, held, strict=True) if h]), y[held].astype(float))
    drawn = {c: int((y == c).sum()) for c in (0, 1)}
    model.shift += float(np.log(shares[1] / drawn[1]) - np.log(shares[0] / drawn[0]))
    return model


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    held_out = fold_of(F.col("doc_id"), 5) == 0
    model = fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality").where(~held_out))
    return score(docs, model, threshold=THRESHOLD).select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", "predicted")
