"""Toxic passages as maximum-scoring segments of token log-odds.

Each word has a log-odds score under an informative Dirichlet prior, backed off
to the word's prefixes. One linear scan of a text's scores finds every maximal
segment; segment scores are put on an extreme-value scale, and the document's
probability comes from that scale by a logistic calibration.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import SortedTable, durable, gathered, remainder_of_crc, words_of


@dataclass(frozen=True)
class ToxicitySpec:
    """``per_class`` bounds the labelled rows of each class that the fit reads.

    ``max_tokens`` bounds the table of telling tokens (those of largest z-score).
    ``prior`` is the total weight of the Dirichlet prior, spread over the tokens
    as they occur in both classes together. ``drift`` is what a token without
    evidence costs at least; it grows until clean text scores below zero.
    ``min_z`` is the significance that a token must reach and ``min_delta`` its
    log-odds, as with many rows any small difference is significant.
    """

    per_class: int = 12_000
    max_tokens: int = 200_000
    prefixes: tuple[int, ...] = (4, 5, 6, 7, 8)
    prior: float = 200.0
    min_z: float = 3.0
    min_delta: float = 1.0
    drift: float = 0.06
    min_segment_nats: float = 1.0


# -------------------------------------------------------------------------- segments
def maximal_segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (start, end exclusive, score) of positive score.

    One pass from left to right that keeps disjoint candidates with the sums
    before and after each, and merges a new one with those that it outgrows.
    Runs of one sign are summed first, so the pass is over runs of evidence.
    """
    scores = np.asarray(scores, dtype=np.float64)
    positive = scores > 0
    if not positive.any():
        return []
    edge = np.flatnonzero(np.diff(np.concatenate(([False], positive, [False])).view(np.int8)))
    begin, stop = edge[0::2], edge[1::2]
    total = np.concatenate(([0.0], np.cumsum(scores)))
    kept: list[list] = []  # start, stop, sum before, sum after, nearest earlier one with a smaller sum before
    for s, e, left, right in zip(begin.tolist(), stop.tolist(), total[begin].tolist(), total[stop].tolist(), strict=True):
        while True:
            j = len(kept) - 1
            while j >= 0 and kept[j][2] >= left:
                j = kept[j][4]
            if j < 0 or kept[j][3] >= right:
                kept.append([s, e, left, right, j])
                break
            s, left = kept[j][0], kept[j][2]
            del kept[j:]
    return [(s, e, right - left) for s, e, left, right, _ in kept]


def karlin_lambda(values: np.ndarray, weights: np.ndarray) -> float:
    """Positive root of E[exp(x * score)] = 1; 1 when no score is positive or the mean isn't negative."""
    p = weights / weights.sum() if weights.sum() else weights
    if not (values > 0).any() or (p[values > 0]).sum() <= 0 or float(p @ values) >= 0:
        return 1.0
    low, high = 0.0, 1.0
    grow = lambda x: float(p @ np.exp(np.minimum(x * values, 500.0))) - 1.0
    while grow(high) < 0 and high < 64:
        high *= 2
    low = 1e-9
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if grow(mid) < 0 else (low, mid)
    return (low + high) / 2


class ToxicityModel:
    """Telling tokens with scores, the extreme-value scale and the calibration."""

    def __init__(self, spec, keys=None, scores=None):
        self.spec = spec
        order = np.argsort(keys) if keys is not None and len(keys) else np.zeros(0, dtype=np.int64)
        self.table = SortedTable(keys[order] if len(order) else np.zeros(0, dtype=np.uint64))
        self.scores = scores[order] if len(order) else np.zeros(0)
        self.drift, self.lam, self.k = spec.drift, 1.0, 0.1
        self.coef = np.array([-4.0, 0.0, 0.0])

    def token_scores(self, hashes: np.ndarray) -> np.ndarray:
        """Best evidence of a word or its prefixes; minus the drift without any."""
        out = np.full(hashes.shape[1], -self.drift)
        for row in hashes:
            known, at = self.table.find(row)
            out[known] = np.maximum(out[known], self.scores[at])
        return out

    def features(self, n_words: int, segments) -> np.ndarray:
        """1, minus log expected number of segments as good as the best, the same summed over the significant ones."""
        size = np.log(self.k * (n_words + 10.0))
        nats = np.array([self.lam * s for _, _, s in segments]) - size
        best = float(nats.max()) if len(nats) else -size
        good = nats[nats > self.spec.min_segment_nats]
        return np.array([1.0, np.clip(best, -20, 40), np.clip(good.sum(), 0, 80)])

    def probability(self, n_words: int, segments) -> float:
        return float(1.0 / (1.0 + np.exp(-np.clip(self.coef @ self.features(n_words, segments), -30, 30))))

    def scan(self, texts):
        """Yields (number of the text, words, segments, starts, ends, raw bytes, offset) over whole texts."""
        for numbers, offsets, data in gathered(texts):
            raw, s, e, h = words_of(data, prefixes=self.spec.prefixes)
            score = self.token_scores(h)
            cut = np.append(np.searchsorted(s, offsets), len(s))
            for j, k in enumerate(numbers):
                a, b = cut[j], cut[j + 1]
                yield k, int(b - a), maximal_segments(score[a:b]), s[a:b], e[a:b], raw, int(offsets[j])


def _fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Ridge-penalised Newton steps."""
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (weight * p * (1 - p))[:, None]).T @ x + np.diag([1e-6] + [1e-3] * (x.shape[1] - 1))
        step = np.linalg.solve(h, x.T @ (weight * (y - p)) - np.array([0.0] + [1e-3] * (x.shape[1] - 1)) * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def fit(docs: DataFrame, labels: DataFrame, spec: ToxicitySpec = ToxicitySpec()) -> ToxicityModel:
    """Fit on the labelled documents given (doc_id, text; doc_id, toxic).

    A document with several labels counts as toxic if any says so. Without both
    classes the model scores every text with a low constant.
    """
    spark = docs.sparkSession
    known = labels.where("toxic is not null and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("y"))
    n = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    model = ToxicityModel(spec)
    if not n.get(0) or not n.get(1):
        return model
    u = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    rate = F.when(F.col("y") == 1, min(1.0, spec.per_class / n[1])).otherwise(min(1.0, spec.per_class / n[0]))
    chosen = known.where(u < rate).limit(3 * spec.per_class)
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    # copies of one text count once, and three quarters fit the tokens
    sample = sample.groupBy(F.xxhash64("text").alias("h")).agg(F.max("y").alias("y"), F.first("text").alias("text")).withColumn("part", F.pmod("h", F.lit(4)))
    sample = durable(sample)  # bounded by per_class; else each of its three uses would read all documents
    prefixes = spec.prefixes

    def tally(batches):
        seen: dict[tuple[int, int], list[np.ndarray]] = {}

        def flush():
            out = []
            for (y, rank), arrays in seen.items():
                keys, counts = np.unique(np.concatenate(arrays), return_counts=True)
                out.append(pd.DataFrame({"key": keys.view(np.int64), "t": counts * y, "c": counts * (1 - y)}))
            seen.clear()
            return out

        held = 0
        for batch in batches:
            ys = batch["y"].tolist()
            for numbers, offsets, data in gathered(batch["text"]):
                _, s, _, h = words_of(data, prefixes=prefixes)
                cut = np.append(np.searchsorted(s, offsets), len(s))
                for j, k in enumerate(numbers):
                    keys = np.unique(h[:, cut[j] : cut[j + 1]])
                    seen.setdefault((int(ys[k]), 0), []).append(keys)
                    held += len(keys)
            if held > 4_000_000:
                yield from flush()
                held = 0
        yield from flush()

    fitting = sample.where("part <> 0").select("y", "text")
    size = {r["y"]: r["n"] for r in fitting.groupBy("y").agg(F.count("*").alias("n")).collect()}
    total_t, total_c = float(size.get(1, 0)), float(size.get(0, 0))
    if not total_t or not total_c:
        return model
    counts = fitting.mapInPandas(tally, "key long, t long, c long").groupBy("key").agg(F.sum("t").alias("t"), F.sum("c").alias("c")).where("t > 0")
    prior = spec.prior * (F.col("t") + F.col("c")) / (total_t + total_c)
    delta = F.log((F.col("t") + prior) / (total_t + spec.prior - F.col("t"))) - F.log((F.col("c") + prior) / (total_c + spec.prior - F.col("c")))
    z = F.col("delta") / F.sqrt(1 / (F.col("t") + F.col("prior")) + 1 / (F.col("c") + F.col("prior")))
    telling = counts.where(F.col("t") + prior > 0).withColumn("prior", prior).withColumn("delta", delta).withColumn("z", z).where((F.col("z") >= spec.min_z) & (F.col("delta") >= spec.min_delta))
    got = telling.orderBy(F.desc("z"), "key").limit(spec.max_tokens).select("key", "delta").toPandas()
    model = ToxicityModel(spec, got["key"].to_numpy(dtype=np.int64).view(np.uint64), np.minimum(got["delta"].to_numpy(dtype=float), 8.0))

    # the other quarter: score distribution of clean tokens, then segments for the calibration
    first = spark.sparkContext.broadcast(model)

    def clean_tokens(batches):
        m = first.value
        for batch in batches:
            for _, _, data in gathered(batch["text"]):
                values, n = np.unique(np.round(m.token_scores(words_of(data, prefixes=prefixes)[3]), 2), return_counts=True)
                yield pd.DataFrame({"value": values, "n": n})

    got = sample.where("part = 0 and y = 0").select("text").mapInPandas(clean_tokens, "value double, n long").groupBy("value").agg(F.sum("n").alias("n")).toPandas()
    values, weights = got["value"].to_numpy(dtype=float), got["n"].to_numpy(dtype=float)
    if weights[values <= 0].sum():
        # segments mean something only where the expected score is negative
        model.drift = max(spec.drift, 2 * float(values[values > 0] @ weights[values > 0]) / float(weights[values <= 0].sum()))
        model.lam = karlin_lambda(np.where(values > 0, values, -model.drift), weights)
    shipped = spark.sparkContext.broadcast(model)

    def measure(batches):
        m = shipped.value
        for batch in batches:
            rows = []
            ys = batch["y"].tolist()
            for k, words, segments, *_ in m.scan(batch["text"]):
                rows.append((int(ys[k]), words, [x[2] for x in segments]))
            yield pd.DataFrame(rows, columns=["y", "n", "score"])

    held = sample.where("part = 0").select("y", "text").mapInPandas(measure, "y int, n long, score array<double>").toPandas()
    if not len(held) or held["y"].nunique() < 2:
        model.coef = np.array([-3.0, 1.0, 0.0])
        return model
    clean = held[held["y"] == 0]
    hits, words = sum(len(r) for r in clean["score"]), float(clean["n"].sum())
    model.k = float(np.clip(hits / max(1.0, words), 1e-4, 1.0))
    x = np.stack([model.features(int(r.n), [(0, 0, s) for s in r.score]) for r in held.itertuples()])
    y = held["y"].to_numpy(dtype=float)
    back = np.where(y == 1, n[1] / max(1, (y == 1).sum()), n[0] / max(1, (y == 0).sum()))
    model.coef = _fit_logistic(x, y, back / back.mean())
    return model


def scorer(spark, model: ToxicityModel):
    """A column function: text -> struct(score, predicted, n_words, n_segments)."""
    shipped = spark.sparkContext.broadcast(model)

    @F.pandas_udf("score double, predicted int, n_words long, n_segments int")
    def score(texts: pd.Series) -> pd.DataFrame:
        m, rows = shipped.value, [None] * len(texts)
        for k, words, segments, *_ in m.scan(texts):
            p = m.probability(words, segments)
            rows[k] = (p, int(p >= 0.5), words, len(segments))
        return pd.DataFrame(rows, columns=["score", "predicted", "n_words", "n_segments"])

    return score


def toxic_spans(docs: DataFrame, model: ToxicityModel, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Every significant segment as (key, start, end, nats); code points, end exclusive."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def spans(batches):
        m = shipped.value
        for batch in batches:
            keys, rows = batch["k"].tolist(), []
            for k, words, segments, s, e, raw, origin in m.scan(batch["t"]):
                for a, b, score in segments:
                    nats = m.lam * score - np.log(m.k * (words + 10.0))
                    if nats > m.spec.min_segment_nats:
                        points = [int(((raw[origin:x] & 0xC0) != 0x80).sum()) for x in (s[a], e[b - 1])]
                        rows.append((keys[k], *points, float(nats)))
            yield pd.DataFrame(rows, columns=["k", "start", "end", "nats"])

    kind = dict(docs.dtypes)[key]
    out = docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInPandas(spans, f"k {kind}, start long, end long, nats double")
    return out.withColumnRenamed("k", key)


def op2_toxicity(spark, sf_dir: str) -> DataFrame:
    """Toxicity of every document; learns from labelled rows with crc32(doc_id) mod 5 <> 0.

    Null and empty texts get the calibrated probability of a text without words.
    Repeated rows each get their score. Other columns are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic")
    model = fit(docs, labels.where(remainder_of_crc("doc_id", 5) != 0))
    held = F.coalesce(remainder_of_crc("doc_id", 5) == 0, F.lit(False))
    out = docs.select("doc_id", held.alias("held_out"), scorer(spark, model)(F.col("text")).alias("p"))
    return out.select("doc_id", "held_out", "p.score", "p.predicted", "p.n_words", "p.n_segments")


def reject_toxic(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents predicted toxic go, the others keep their columns.

    Null and empty texts have no evidence and stay, and without labels of both
    classes every document does. Repeated rows share their fate. Further columns
    pass through, whatever their names; an empty table stays empty.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic")
    model = fit(docs, labels.where(remainder_of_crc("doc_id", 5) != 0))
    return docs.where(scorer(spark, model)(F.col("text"))["predicted"] == 0)
