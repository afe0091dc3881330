"""Language identification: multinomial logistic regression on TF-IDF character n-grams, fitted by FTRL, calibrated by a temperature."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fold_of, small_batches, table, text_blocks, tidied
from .ftrl import FtrlLogistic

FEATURE_BITS, ORDERS = 16, (1, 2, 3)
#: Bound on the rows of each language that the weights are fitted on; document frequencies are of all learnable rows.
TRAIN_ROWS_PER_LANGUAGE = 1_000
EPOCHS, SCALE, UNDETERMINED = 3, 20.0, "und"
_MULTIPLIERS = (np.uint32(0x9E3779B1), np.uint32(0x85EBCA77), np.uint32(0xC2B2AE3D))


def gram_features(texts: list[bytes], bits: int = FEATURE_BITS) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each order: feature numbers of the character n-grams inside the texts in turn, and where each text's begin (and the end)."""
    marks = "\n".join(t.decode() for t in texts) + "\n"
    points = np.frombuffer(marks.encode("utf-32-le"), np.uint32)
    lengths = np.array([len(t.decode()) if len(t) else 0 for t in texts], np.int64)
    begins = np.cumsum(np.append(0, lengths + 1))
    out = []
    for n in ORDERS:
        h = np.full(len(points) - n + 1, n, np.uint32)
        for j in range(n):
            h = (h ^ points[j : len(points) - n + 1 + j]) * _MULTIPLIERS[j]
            h ^= h >> np.uint32(15)
        inside = np.ones(len(h), bool)
        for back in range(1, n + 1):  # grams that reach over a text's end
            at = begins[1:] - back
            inside[at[(at >= 0) & (at < len(h))]] = False
        kept = np.cumsum(np.append(0, inside))
        out.append(((h[inside] >> np.uint32(32 - bits)).astype(np.int64), kept[np.minimum(begins, len(h))]))
    return out


@dataclass
class LanguageModel:
    languages: list[str]
    table: np.ndarray  # features x languages: weight times idf
    bias: np.ndarray
    temperature: float = 1.0
    bits: int = field(default=FEATURE_BITS)

    def margins(self, texts: list[bytes]) -> np.ndarray:
        total, sums = np.zeros(len(texts)), np.zeros((len(texts), len(self.languages)))
        columns = [np.ascontiguousarray(self.table[:, c], np.float32) for c in range(len(self.languages))]
        for feature, begins in gram_features(texts, self.bits):
            total += np.diff(begins)
            for c, column in enumerate(columns):
                running = np.zeros(len(feature) + 1)
                np.cumsum(column[feature], out=running[1:], dtype=np.float64)
                sums[:, c] += running[begins[1:]] - running[begins[:-1]]
        return SCALE * sums / np.maximum(total, 1)[:, None] + self.bias

    def probabilities(self, texts: list[bytes]) -> np.ndarray:
        m = self.margins(texts) / self.temperature
        e = np.exp(m - m.max(1, keepdims=True))
        return e / e.sum(1, keepdims=True)


def lowered(text: Column) -> Column:
    return F.lower(F.coalesce(text, F.lit("")))


def document_frequencies(docs: DataFrame, bits: int = FEATURE_BITS) -> tuple[np.ndarray, int]:
    """In how many of the texts ``t`` each feature occurs, and the number of texts. A task sends one count a feature at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, rows, seen = np.zeros(1 << bits, np.int64), 0, np.zeros(1 << bits, bool)
        for batch in batches:
            for _, _, texts in text_blocks(batch, "t"):
                grams = gram_features(texts, bits)
                for i in range(len(texts)):
                    seen[:] = False
                    for feature, begins in grams:
                        seen[feature[begins[i] : begins[i + 1]]] = True
                    counts += seen
                rows += len(texts)
        at = np.flatnonzero(counts)
        yield pa.record_batch([pa.array(np.append(at, -1)), pa.array(np.append(counts[at], rows))], names=["f", "n"])

    got = docs.select("t").transform(small_batches).mapInArrow(tidied(run), "f long, n long").groupBy("f").agg(F.sum("n").alias("n")).toArrow()  # a row a feature
    f, n = np.asarray(got["f"]), np.asarray(got["n"])
    df = np.zeros(1 << bits)
    df[f[f >= 0]] = n[f >= 0]
    return df, int(n[f < 0].sum())


def _counted(rows: DataFrame, bits: int) -> DataFrame:
    """(y, h, f array<int>, n array<int>) of ``rows(y, h, t)``: the distinct features of each text and their counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                grams = gram_features(texts, bits)
                each = [np.unique(np.concatenate([f[s[i] : s[i + 1]] for f, s in grams]), return_counts=True) for i in range(len(texts))]
                part = batch.slice(a, b - a)
                lists = [pa.array([e[j].astype(np.int32) for e in each], pa.list_(pa.int32())) for j in (0, 1)]
                yield pa.record_batch([part.column(0), part.column(1), *lists], names=["y", "h", "f", "n"])

    return rows.select("y", "h", "t").transform(small_batches).mapInArrow(tidied(run), "y string, h long, f array<int>, n array<int>")


def fit(docs: DataFrame, language: str = "lang", key: str = "doc_id", text: str = "text", rows: int = TRAIN_ROWS_PER_LANGUAGE, bits: int = FEATURE_BITS) -> LanguageModel | None:
    """Learn from every row with a language: document frequencies from all of them, weights from a bounded sample of each language.

    A quarter of the sample only sets the temperature. None if no row has a language.
    """
    known = docs.where(F.col(language).isNotNull()).select(F.col(language).alias("y"), F.xxhash64(F.lit(11), key).alias("h"), lowered(F.col(text)).alias("t"))
    sizes = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row a language
    if not sizes:
        return None
    languages = sorted(sizes)
    df, total = document_frequencies(known, bits)
    idf = np.log((1 + total) / (1 + df)) + 1
    share = F.create_map(*[x for y in languages for x in (F.lit(y), F.lit(int(min(1.0, rows / sizes[y]) * (1 << 30))))])
    sample = _counted(known.where(F.pmod("h", F.lit(1 << 30)) < F.try_element_at(share, F.col("y"))), bits).toArrow().sort_by([("h", "ascending"), ("y", "ascending")])
    y = np.array([languages.index(v) for v in sample["y"].to_pylist()], np.int64)
    data = []
    for f, n in zip(sample["f"], sample["n"], strict=True):
        at, count = np.asarray(f.values), np.asarray(n.values).astype(float)
        data.append((at, SCALE * count / max(1.0, count.sum()) * idf[at]))
    tune = np.arange(len(y)) % 4 == 3
    model = FtrlLogistic(1 << bits, len(languages), alpha=0.5, l1=0.02, l2=0.02)
    targets, dice = np.eye(len(languages)), np.random.default_rng(2)
    learn = np.flatnonzero(~tune)
    if len(languages) > 1:
        for _ in range(EPOCHS):
            for i in dice.permutation(learn):
                model.learn(*data[i], targets[y[i]])
    w, b = model.weights()
    fitted = LanguageModel(languages, (w * idf[:, None]).astype(np.float32), b, 1.0, bits)
    fitted.temperature = _temperature(np.array([x @ w[at] + b for (at, x), t in zip(data, tune, strict=True) if t]).reshape(-1, len(languages)), y[tune])
    return fitted


def _temperature(margins: np.ndarray, y: np.ndarray) -> float:
    """The temperature of least log loss, on a fine geometric grid."""
    best = (np.inf, 1.0)
    for t in np.geomspace(0.05, 20, 121):
        m = margins / t
        m = m - m.max(1, keepdims=True) if len(m) else m
        loss = (np.log(np.exp(m).sum(1)) - m[np.arange(len(y)), y]).sum() + 1e-3 * abs(np.log(t))
        best = min(best, (float(loss), float(t)))
    return best[1]


def identify(docs: DataFrame, model: LanguageModel | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, lang_pred, score) of every row.

    Null texts and texts without a letter are ``und`` with score 0, as is all without a model. Texts are read whole; repeated rows
    give repeated results, equal probabilities the language first in order; an empty table gives an empty result; other columns
    play no part.
    """
    kind = docs.schema[key].dataType.simpleString()
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                part, m = batch.slice(a, b - a), sent.value
                lettered = np.asarray(part.column(2)).astype(bool)
                if m is None:
                    names, best = [UNDETERMINED] * len(texts), np.zeros(len(texts))
                else:
                    p = m.probabilities(texts)
                    names = [m.languages[i] if ok else UNDETERMINED for i, ok in zip(p.argmax(1), lettered, strict=True)]
                    best = np.where(lettered, p.max(1), 0.0)
                yield pa.record_batch([part.column(0), pa.array(names, pa.string()), pa.array(best)], names=["k", "lang_pred", "score"])

    lettered = F.coalesce(F.col(text).rlike(r"\p{L}"), F.lit(False))
    found = docs.select(F.col(key).alias("k"), lowered(F.col(text)).alias("t"), lettered.alias("l")).transform(small_batches).mapInArrow(tidied(run), f"k {kind}, lang_pred string, score double")
    return found.withColumnRenamed("k", key)


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    held_out = fold_of(F.col("doc_id"), 5) == 0
    return identify(docs, fit(docs.where(~held_out))).select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "lang_pred", "score")
