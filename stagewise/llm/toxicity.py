"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fold_of, give_back, mix64, small_batches, span_hashes, table, text_blocks, tidied, word_spans
from .ftrl import FtrlLogistic

FEATURE_BITS = 20
#: Bound on the labelled rows of either label that the model is fitted on; the rows are chosen by a hash of their id.
TRAIN_ROWS_PER_LABEL = 4_000
#: Bound on the bytes of their texts: a text has about five features a word, at four bytes a feature.
TRAIN_BYTES = 128 << 20
EPOCHS, THRESHOLD = 5, 0.3

#: Words also count by their first bytes, so that inflected and compound forms share evidence.
STEM_BYTES = (4, 6)

_BREAK = np.ones(256, bool)  # words here are runs of ASCII letters, digits and whatever is beyond ASCII
_BREAK[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False
_KEEP = bytes(10 if _BREAK[b] else b for b in range(256))


def word_features(texts: list[bytes], bits: int = FEATURE_BITS) -> tuple[np.ndarray, np.ndarray]:
    """(text number, feature number) of every word, stem, pair of neighbours, and pair with one word between; A-Z lower-cased."""
    joined, starts, ends, counts = word_spans([t.lower().translate(_KEEP) for t in texts])
    words = span_hashes(np.frombuffer(joined, np.uint8), starts, ends)
    doc = np.repeat(np.arange(len(texts)), counts)
    shift = np.uint64(64 - bits)
    docs, found = [doc], [words >> shift]
    for stem in STEM_BYTES:
        cut = span_hashes(np.frombuffer(joined, np.uint8), starts, np.minimum(ends, starts + stem))
        docs.append(doc)
        found.append(mix64(cut + np.uint64(stem)) >> shift)
    for gap, salt in ((1, 0x9E3779B97F4A7C15), (2, 0xC2B2AE3D27D4EB4F)):
        same = doc[:-gap] == doc[gap:]
        pair = mix64(words[:-gap] * np.uint64(salt) + (words[gap:] ^ (words[gap:] >> np.uint64(31))) + np.uint64(gap))
        docs.append(doc[:-gap][same])
        found.append(pair[same] >> shift)
    return np.concatenate(docs), np.concatenate(found).astype(np.int64)


@dataclass
class ToxicityModel:
    """The features whose weight is not zero. L1 keeps them few, so the model can be sent to every executor."""

    at: np.ndarray
    weight: np.ndarray
    bias: float
    bits: int = FEATURE_BITS

    def scores(self, texts: list[bytes]) -> np.ndarray:
        if not hasattr(self, "_dense"):
            self._dense = np.zeros(1 << self.bits)
            self._dense[self.at] = self.weight
        doc, feature = word_features(texts, self.bits)
        hit = self._dense[feature] != 0
        once = np.unique((doc[hit].astype(np.int64) << self.bits) | feature[hit])
        margin = self.bias + np.bincount(once >> self.bits, self._dense[once & ((1 << self.bits) - 1)], minlength=len(texts))
        return 1 / (1 + np.exp(-np.clip(margin, -500, 500)))


def _distinct_features(rows: DataFrame, bits: int) -> DataFrame:
    """(y, f array<int>) of ``rows(y, t)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                doc, feature = word_features(texts, bits)
                once = np.unique((doc.astype(np.int64) << bits) | feature)
                ends = np.searchsorted(once >> bits, np.arange(len(texts) + 1))
                flat = pa.array((once & ((1 << bits) - 1)).astype(np.int32))
                yield pa.record_batch([batch.column(0).slice(a, b - a), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), flat)], names=["y", "f"])

    return rows.transform(small_batches).mapInArrow(tidied(run), "y int, f array<int>")


def labelled_sample(labels: DataFrame, label: str, key: str, bound: int) -> DataFrame:
    """(key, y): about ``bound`` of the rows with a label, chosen by a hash of their key; all of them if there are no more."""
    known = labels.where(F.col(label).isNotNull() & F.col(key).isNotNull()).select(key, F.col(label).cast("int").alias("y"))
    share = bound / max(1, known.count())
    return known if share >= 1 else known.where(F.pmod(F.xxhash64(F.lit(17), key), F.lit(1 << 30)) < int(share * (1 << 30)))


def labelled_texts(docs: DataFrame, labels: DataFrame, label: str, key: str, text: str, rows: int, most: int) -> DataFrame:
    """(y, t, h): whole texts with label 1 or 0, about ``rows`` of each and at most about ``most`` bytes in all, chosen by a hash of their key."""
    of = lambda y: labelled_sample(labels.where(F.col(label) == y), label, key, rows)
    sample = of(1).unionByName(of(0)).select(F.col(key).alias("k"), "y")
    texts = docs.select(F.col(key).alias("k"), F.coalesce(text, F.lit("")).alias("t")).join(F.broadcast(sample), "k").select("y", "t", F.xxhash64(F.lit(5), "k").alias("h"))
    size = texts.agg(F.sum(F.octet_length("t").cast("long"))).first()[0] or 0
    return texts if size <= most else texts.where(F.pmod("h", F.lit(1 << 30)) < int(most / size * (1 << 30)))


def fit(
    docs: DataFrame, labels: DataFrame, label: str = "toxic", key: str = "doc_id", text: str = "text", rows: int = TRAIN_ROWS_PER_LABEL, bits: int = FEATURE_BITS, epochs: int = EPOCHS, most: int = TRAIN_BYTES
) -> ToxicityModel:
    """Fit on whole texts of a bounded sample of the labelled rows.

    Null labels and labels other than 0 and 1 are left out, as are labels whose document is absent; a null text counts as empty, a
    repeated row as often as it is there. Without texts of both labels every score is that of no evidence, zero.
    """
    got = _distinct_features(labelled_texts(docs, labels, label, key, text, rows, most).select("y", "t"), bits).toArrow().combine_chunks()
    y = np.asarray(got["y"]).astype(float)
    if len(set(y)) < 2:
        return ToxicityModel(np.zeros(0, np.int64), np.zeros(0), -np.inf, bits)
    features = got["f"].combine_chunks() if isinstance(got["f"], pa.ChunkedArray) else got["f"]
    flat, ends = np.asarray(features.flatten()), np.asarray(features.offsets)
    model = FtrlLogistic(1 << bits, alpha=0.2, l1=8.0, l2=1.0)
    # the order of learning must not follow the order in which tasks ended
    order = np.lexsort((np.add.reduceat(np.append(flat, 0), ends[:-1]) * (np.diff(ends) > 0), np.diff(ends), y))
    dice = np.random.default_rng(1)
    for _ in range(epochs):
        for i in dice.permutation(order.copy()):
            at = flat[ends[i] : ends[i + 1]]
            model.learn(at, np.ones(len(at)), y[i])
    w, b = model.weights()
    at = np.flatnonzero(w[:, 0])
    fitted = ToxicityModel(at, w[at, 0], float(b[0]), bits)
    del got, features, flat, ends, model, w
    give_back()  # the driver's later stages have no use for the sample's memory
    return fitted


def score(docs: DataFrame, model, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """(key, score, predicted) of every row.

    Null counts as the empty text, which gets the score of the bias alone. Texts are scored whole; repeated rows give repeated
    results and equal texts equal scores; an empty table gives an empty result; other columns play no part.
    """
    kind = docs.schema[key].dataType.simpleString()
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                yield pa.record_batch([batch.column(0).slice(a, b - a), pa.array(sent.value.scores(texts))], names=["k", "score"])

    found = docs.select(F.col(key).alias("k"), F.col(text).alias("t")).transform(small_batches).mapInArrow(tidied(run), f"k {kind}, score double")
    return found.select(F.col("k").alias(key), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def reject_toxic(docs: DataFrame, model: ToxicityModel, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows that the model does not hold for toxic, all columns as they were, whatever they are called.

    Each row is judged where it stands, repeated rows alike; null counts as the empty text; an empty table gives an empty result.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)
    plain, of = docs.toDF(*(f"c{i}" for i in range(len(docs.columns)))), f"c{docs.columns.index(text)}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_blocks(batch, of):
                yield batch.slice(a, b - a).filter(pa.array(sent.value.scores(texts) < threshold))

    return plain.transform(small_batches).mapInArrow(tidied(run), plain.schema).toDF(*docs.columns)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    held_out = fold_of(F.col("doc_id"), 4) == 2
    model = fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic").where(~held_out))
    return score(docs, model).select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", "predicted")
