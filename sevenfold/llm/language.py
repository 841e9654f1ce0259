"""Language identification by sparse multinomial logistic regression.

Features are TF-IDF weights of character 1- to 3-grams hashed to a fixed number
of buckets. Document frequencies come from every training row; the weights are
fitted by follow-the-regularised-leader with an elastic-net penalty on a sample
bounded by ``LanguageSpec.per_language`` rows of each language, and a
temperature is calibrated on rows that the weights never saw.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import remainder_of_crc


@dataclass(frozen=True)
class LanguageSpec:
    """``per_language`` bounds the fitting sample; ``bits`` fixes the model's size."""

    bits: int = 15
    per_language: int = 1200
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 2e-3
    l2: float = 1e-3
    epochs: int = 3
    piece_chars: int = 1 << 20


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """True for the code points that are letters."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), dtype=bool, count=0x110000)


#: One odd multiplier for each place in an n-gram.
_PLACE = np.array([0x85EBCA6B, 0xC2B2AE35, 0x27D4EB2F], dtype=np.uint32)


def ngram_counts(text: str | None, bits: int, piece: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and counts of the whole text's character n-grams; none if it has no letter.

    Runs of anything but letters count as one blank, as does either end.
    """
    size = 1 << bits
    total = np.zeros(size, dtype=np.int64)
    any_letter, tail = False, np.array([32], dtype=np.uint32)
    text = text or ""
    for at in range(0, len(text), piece):
        code = np.frombuffer(text[at : at + piece].lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        letter = _letters()[code]
        any_letter = any_letter or bool(letter.any())
        code = np.where(letter, code, np.uint32(32))
        code = np.concatenate((tail, code, [np.uint32(32)] if at + piece >= len(text) else [])).astype(np.uint32)
        code = code[np.concatenate(([True], (code[1:] != 32) | (code[:-1] != 32)))]
        fresh = 0 if at == 0 else min(len(tail), len(code))
        h = np.zeros(len(code), dtype=np.uint32)
        for n in range(3):
            if len(code) <= n:
                break
            h = h[: len(code) - n] + (code[n:] + np.uint32(1)) * _PLACE[n]
            # n-grams that lie wholly in the carried tail were counted before
            begin = max(0, fresh - n)
            mixed = (h[begin:] ^ (h[begin:] >> np.uint32(15))) * np.uint32(0x9E3779B1)
            total += np.bincount(mixed >> np.uint32(32 - bits), minlength=size)
        tail = code[-2:]
    if not any_letter:
        return np.zeros(0, dtype=np.int32), np.zeros(0, dtype=np.int32)
    idx = np.flatnonzero(total)
    return idx.astype(np.int32), total[idx].astype(np.int32)


def _weights(idx, counts, idf):
    v = np.log1p(counts) * idf[idx]
    norm = np.sqrt(float(v @ v))
    return v / norm if norm else v


def _softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


class LanguageModel:
    """Weights (buckets x languages), idf and temperature; the size is fixed by ``bits``."""

    def __init__(self, languages, weights, idf, temperature, spec):
        self.languages, self.weights, self.idf = list(languages), weights, idf
        self.temperature, self.spec = temperature, spec

    def logits(self, idx, counts) -> np.ndarray:
        return _weights(idx, counts, self.idf) @ self.weights[idx]

    def predict(self, text: str | None) -> tuple[str, float]:
        """The language and its calibrated probability; ``und`` and 0 without a letter."""
        idx, counts = ngram_counts(text, self.spec.bits, self.spec.piece_chars)
        if not len(idx) or not self.languages:
            return "und", 0.0
        p = _softmax(self.logits(idx, counts) / self.temperature)
        best = int(p.argmax())
        return self.languages[best], float(p[best])


def _fit_ftrl(rows, n_lang, idf, spec: LanguageSpec) -> np.ndarray:
    """Per-coordinate proximal updates; only the coordinates of a row are touched."""
    size = 1 << spec.bits
    z = np.zeros((size, n_lang))
    squares = np.zeros((size, n_lang))

    def lazy(zi, ni):
        shrunk = np.sign(zi) * np.maximum(np.abs(zi) - spec.l1, 0.0)
        return -shrunk / ((spec.beta + np.sqrt(ni)) / spec.alpha + spec.l2)

    prepared = [(y, idx, _weights(idx, counts, idf)) for y, idx, counts in rows if len(idx)]
    for epoch in range(spec.epochs):
        for k in np.random.default_rng(epoch).permutation(len(prepared)):
            y, idx, v = prepared[k]
            zi, ni = z[idx], squares[idx]
            w = lazy(zi, ni)
            slope = _softmax(v @ w)
            slope[y] -= 1.0
            g = v[:, None] * slope[None, :]
            step = (np.sqrt(ni + g * g) - np.sqrt(ni)) / spec.alpha
            z[idx] = zi + g - step * w
            squares[idx] = ni + g * g
    return lazy(z, squares)


def _calibrate(model: LanguageModel, rows) -> float:
    """Temperature of least log loss, by golden-section search."""
    rows = [(y, model.logits(idx, counts)) for y, idx, counts in rows if len(idx)]
    if not rows:
        return 1.0
    y, x = np.array([r[0] for r in rows]), np.stack([r[1] for r in rows])

    def loss(log_t):
        return -np.log(np.maximum(_softmax(x / np.exp(log_t))[np.arange(len(y)), y], 1e-12)).mean()

    low, high, ratio = -4.0, 3.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = high - ratio * (high - low), low + ratio * (high - low)
        low, high = (low, b) if loss(a) < loss(b) else (a, high)
    return float(np.exp((low + high) / 2))


def fit(train: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", spec: LanguageSpec = LanguageSpec()) -> LanguageModel:
    """Fit on the rows with a language. Rows without a letter teach nothing.

    An empty table gives a model without languages, which answers ``und``.
    """
    spark = train.sparkSession
    rows = train.select(F.col(key).alias("k"), F.col(text).alias("t"), F.col(lang).alias("y")).where("y is not null")
    totals = {r["y"]: r["n"] for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
    languages = sorted(totals)
    size, bits, piece = 1 << spec.bits, spec.bits, spec.piece_chars
    if not languages:
        return LanguageModel([], np.zeros((size, 0)), np.ones(size), 1.0, spec)

    def frequencies(batches):
        seen, n = np.zeros(size, dtype=np.int64), 0
        for batch in batches:
            for value in batch["t"]:
                idx, _ = ngram_counts(value, bits, piece)
                seen[idx] += 1
                n += 1
        if n:
            at = np.flatnonzero(seen)
            yield pd.DataFrame({"bucket": np.append(at, -1), "df": np.append(seen[at], n)})

    table = rows.select("t").mapInPandas(frequencies, "bucket long, df long").groupBy("bucket").agg(F.sum("df").alias("df")).toPandas()
    frequency, n_docs = np.zeros(size), 0
    for b, d in zip(table["bucket"], table["df"], strict=True):
        if b < 0:
            n_docs = d
        else:
            frequency[b] = d
    idf = np.log((1.0 + n_docs) / (1.0 + frequency)) + 1.0

    # the fitting sample: a hash threshold for each language, then a hard bound
    share = spark.createDataFrame([(y, min(1.0, spec.per_language / n)) for y, n in totals.items()], "y string, share double")
    draw = F.pmod(F.xxhash64("k", "t"), F.lit(1 << 30)) / float(1 << 30)
    sample = rows.join(F.broadcast(share), "y").withColumn("u", draw).where("u < share").withColumn("u", F.col("u") / F.col("share"))

    def features(batches):
        for batch in batches:
            got = [ngram_counts(v, bits, piece) for v in batch["t"]]
            yield pd.DataFrame({"y": batch["y"], "u": batch["u"], "idx": [g[0] for g in got], "cnt": [g[1] for g in got]})

    # features first, so that all tasks share them and no text is gathered
    found = sample.select("y", "u", "t").mapInPandas(features, "y string, u double, idx array<int>, cnt array<int>")
    most = int(1.5 * spec.per_language * len(languages)) + 1
    number = {y: k for k, y in enumerate(languages)}
    got = found.orderBy("u", "y").limit(most).toPandas().sort_values(["u", "y"])
    data = [(number[y], np.asarray(i), np.asarray(c)) for y, i, c in zip(got["y"], got["idx"], got["cnt"], strict=True)]
    held = [r for k, r in enumerate(data) if k % 5 == 0]
    fitted = [r for k, r in enumerate(data) if k % 5 or len(data) < 50]
    model = LanguageModel(languages, _fit_ftrl(fitted, len(languages), idf, spec), idf, 1.0, spec)
    model.temperature = _calibrate(model, held)
    return model


def predictor(spark, model: LanguageModel):
    """A column function: text -> struct(lang_pred, score). The model goes out once per executor."""
    shipped = spark.sparkContext.broadcast(model)

    @F.pandas_udf("lang_pred string, score double")
    def predict(texts: pd.Series) -> pd.DataFrame:
        m = shipped.value
        return pd.DataFrame([m.predict(t) for t in texts], columns=["lang_pred", "score"])

    return predict


def identify(docs: DataFrame, model: LanguageModel, text: str = "text") -> Column:
    """Column with the predicted language of the whole text."""
    return predictor(docs.sparkSession, model)(F.col(text))


def op1_language(spark, sf_dir: str) -> DataFrame:
    """Predicted language of every document; learns from crc32(doc_id) mod 4 <> 2.

    Null text, or text without a letter: ``und``, score 0. Repeated rows each
    get their answer. Other columns of the table are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    fold = remainder_of_crc("doc_id", 4)
    model = fit(docs.where(~(F.coalesce(fold, F.lit(-1)) == 2)))
    return docs.select("doc_id", F.coalesce(fold == 2, F.lit(False)).alias("held_out"), identify(docs, model).alias("p")).select("doc_id", "held_out", "p.lang_pred", "p.score")
