"""Benchmark decontamination by a prefix-filtered set join.

A benchmark item is cut to windows of ten words. The words of a window are
ordered by their rarity in the documents. As a window must be contained whole,
its necessary prefix is its rarest word: a document holds the window only where
it holds that word. The word's place in the window bounds where the window may
begin, the text's length bounds where it may end. What remains joins the table
of windows, where the words are compared one by one.

Neither the benchmark nor its windows are gathered anywhere: the documents meet
them in a join. What goes out to every task are tables of bits, at most
2**``MOST_BITS`` each whatever the benchmark's size, that spare the documents
most words that begin nothing; a bit set by chance only adds a candidate.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import durable, gathered, mix64, small_side, words_of

WINDOW = 10
#: Bits for each value that a table of bits aims at, and the bits that it has at most (32 MB).
BITS_A_VALUE, MOST_BITS = 64, 28
#: Rows of a frame that goes back to Spark.
FRAME_ROWS = 20_000
#: Shares into which hot windows are dealt where windows and candidates meet by shuffle.
SALTS = 16
#: A word as in the contract, before lower-casing.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def _place_keys(n: int) -> np.ndarray:
    return mix64(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def window_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of every run of ``n`` words from the words' hashes."""
    if len(h) < n:
        return np.zeros(0, dtype=np.uint64)
    total = np.zeros(len(h) - n + 1, dtype=np.uint64)
    for k, key in enumerate(_place_keys(n)):
        total += mix64(h[k : len(h) - n + 1 + k] ^ key)
    return total


# --------------------------------------------------------------------- tables of bits
class BitTable:
    """Whether the low bits of a value are those of any value put in."""

    def __init__(self, bits: int, places: np.ndarray, words: np.ndarray):
        self.mask = np.uint64((1 << bits) - 1)
        self.words = np.zeros(1 << (bits - 6), dtype=np.uint64)
        self.words[places] = words
        self._flags = None  # made where it is used, so that it isn't shipped

    def may_have(self, values: np.ndarray) -> np.ndarray:
        at = values & self.mask
        if len(self.words) > 1 << 18:
            return (self.words[at >> np.uint64(6)] >> (at & np.uint64(63))) & np.uint64(1) == 1
        if self._flags is None:
            self._flags = np.unpackbits(self.words.view(np.uint8), bitorder="little").astype(bool)
        return self._flags[at]


def bit_table(values: DataFrame, column: str = "x") -> BitTable:
    """The table of a checkpointed column of longs. The driver gets one row for each 64 bits that aren't all zero."""
    n = values.count()
    bits = min(MOST_BITS, max(16, math.ceil(math.log2(max(1, n) * BITS_A_VALUE))))
    place = F.col(column).bitwiseAND(F.lit((1 << bits) - 1))
    marks = values.select(F.shiftright(place, 6).alias("w"), F.expr(f"shiftleft(1L, cast({column} & 63 AS INT))").alias("b"))
    got = marks.groupBy("w").agg(F.bit_or("b").alias("b")).toPandas()
    return BitTable(bits, got["w"].to_numpy(dtype=np.int64), got["b"].to_numpy(dtype=np.int64).view(np.uint64))


# --------------------------------------------------------------------------- windows
def item_windows(benchmark: DataFrame, item: str = "item_id", text: str = "text") -> DataFrame:
    """(item, n, whole, piece, h) of every distinct window of every item: its hash, words joined by a space, and words' hashes."""

    def cut(batches):
        for batch in batches:
            rows = []
            for name, value in zip(batch["i"], batch["t"], strict=True):
                raw, s, e, hs = words_of(value.encode("utf-8", "surrogatepass") if isinstance(value, str) else b"")
                data, h = raw.tobytes(), hs[0]
                n = min(WINDOW, len(h))
                whole = window_hashes(h, n) if n else h
                for k in range(len(whole)):
                    rows.append((name, n, int(whole[k : k + 1].view(np.int64)[0]), b" ".join(data[a:b] for a, b in zip(s[k : k + n].tolist(), e[k : k + n].tolist(), strict=True)), h[k : k + n].view(np.int64)))
                    if len(rows) >= FRAME_ROWS:
                        yield pd.DataFrame(rows, columns=["item", "n", "whole", "piece", "h"])
                        rows = []
            if rows:
                yield pd.DataFrame(rows, columns=["item", "n", "whole", "piece", "h"])

    rows = benchmark.select(F.col(item).cast("string").alias("i"), F.col(text).alias("t")).distinct()
    return rows.mapInPandas(cut, "item string, n int, whole long, piece binary, h array<long>").dropDuplicates(["item", "n", "whole", "piece"])


def word_frequencies(docs: DataFrame, vocabulary: DataFrame, text: str = "text") -> DataFrame:
    """(word, seen): occurrences in all documents of the word hashes in the checkpointed ``vocabulary`` (x)."""
    shipped = docs.sparkSession.sparkContext.broadcast(bit_table(vocabulary))

    def count(batches):
        held, size = [], 0

        def tally():
            word, n = np.unique(np.concatenate(held), return_counts=True)
            return pd.DataFrame({"word": word.view(np.int64), "n": n})

        for batch in batches:
            for _, _, data in gathered(batch["t"]):
                h = words_of(data)[3][0]
                held.append(h[shipped.value.may_have(h)])
                size += len(held[-1])
                if size > 1 << 20:
                    yield tally()
                    held, size = [], 0
        if held:
            yield tally()

    partly = docs.select(F.col(text).alias("t")).mapInPandas(count, "word long, n long").groupBy("word").agg(F.sum("n").alias("seen"))
    return partly.join(small_side(vocabulary), F.col("word") == F.col("x"), "left_semi")


def rarest_words(windows: DataFrame, docs: DataFrame, text: str = "text") -> DataFrame:
    """(n, whole, piece, head, place, c) of the distinct windows: the rarest word, its place, and a number for (n, place)."""
    own = windows.select("n", "whole", "piece", "h").dropDuplicates(["n", "whole", "piece"])
    own = durable(own)
    vocabulary = durable(own.select(F.explode("h").alias("x")).distinct())
    seen = durable(word_frequencies(docs, vocabulary, text))
    words = own.select("n", "whole", "piece", F.posexplode("h").alias("place", "x")).join(small_side(seen), F.col("x") == F.col("word"), "left")
    rank = F.struct(F.coalesce("seen", F.lit(0)).alias("seen"), F.col("x").alias("head"), "place")
    best = words.groupBy("n", "whole", "piece").agg(F.min(rank).alias("r"))
    return durable(best.select("n", "whole", "piece", "r.head", "r.place", F.xxhash64("n", "r.place").alias("c")))


def candidates(docs: DataFrame, rare: DataFrame, text: str = "text") -> DataFrame:
    """(digest, start, n, whole, piece) wherever a text may hold a window: its rarest word is there and the window fits."""
    spark = docs.sparkSession
    kinds = [(r.n, r.place, np.uint64(r.c & ((1 << 64) - 1))) for r in rare.select("n", "place", "c").distinct().collect()]  # WINDOW * (WINDOW + 1) / 2 at most
    tables = [durable(rare.select(x.alias("x")).distinct()) for x in (F.col("head"), F.col("head").bitwiseXOR(F.col("c")), F.col("whole"))]
    shipped = spark.sparkContext.broadcast(tuple(bit_table(t) for t in tables))

    def search(batches):
        heads, placed, known = shipped.value
        for batch in batches:
            digests = batch["d"]
            for numbers, offsets, buffer in gathered(batch["t"]):
                raw, s, e, hs = words_of(buffer)
                h = hs[0]
                near = np.flatnonzero(heads.may_have(h))
                if not len(near):
                    continue
                data, cut = raw.tobytes(), np.append(np.searchsorted(s, offsets), len(s))
                bound = np.repeat(cut[1:], np.diff(cut))
                rows = []
                for n, place, c in kinds:
                    start = near[placed.may_have(h[near] ^ c)] - place
                    start = start[start >= 0]
                    start = start[start + n <= bound[start]]
                    if not len(start):
                        continue
                    value = np.zeros(len(start), dtype=np.uint64)
                    for k, key in enumerate(_place_keys(n)):
                        value += mix64(h[start + k] ^ key)
                    hit = known.may_have(value)
                    for a, w in zip(start[hit].tolist(), value[hit].view(np.int64).tolist(), strict=True):
                        j = int(np.searchsorted(cut, a, side="right")) - 1
                        rows.append((digests[numbers[j]], a - int(cut[j]), n, w, b" ".join(data[x:y] for x, y in zip(s[a : a + n].tolist(), e[a : a + n].tolist(), strict=True))))
                        if len(rows) >= FRAME_ROWS:
                            yield pd.DataFrame(rows, columns=["digest", "start", "n", "whole", "piece"])
                            rows = []
                if rows:
                    yield pd.DataFrame(rows, columns=["digest", "start", "n", "whole", "piece"])

    return docs.select(digest(text).alias("d"), F.col(text).alias("t")).mapInPandas(search, "digest string, start long, n int, whole long, piece binary")


def digest(text: str = "text"):
    """What a text is known by: equal texts hold the same windows."""
    return F.sha2(F.coalesce(F.col(text), F.lit("")), 256)


def contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text") -> DataFrame:
    """(digest, n_hit, n_items, items_sha256) of every text that holds a window, by whole texts; checkpointed.

    Null texts, and items without words, have no windows. Items without an id are
    searched for, but have no id to name and no place among the items. A window
    that very many texts hold, and that many items share, is dealt to several
    tasks where the windows are too many to be broadcast.
    """
    windows = durable(item_windows(benchmark, item, item_text))
    rare = rarest_words(windows, docs, text)
    found = candidates(docs, rare, text).distinct()
    side = small_side(windows.select("n", "whole", "piece", "item"))
    keys = ["n", "whole", "piece"]
    if not _broadcasts(side):
        side = side.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        found = found.withColumn("salt", F.pmod(F.xxhash64("digest", "start"), F.lit(SALTS)).cast("int"))
        keys.append("salt")
    hits = durable(found.join(side, keys).select("digest", "start", "n", "item"))
    covered = hits.select("digest", F.explode(F.sequence(F.col("start"), F.col("start") + F.col("n") - 1)).alias("at")).distinct()
    covered = covered.groupBy("digest").agg(F.count("*").alias("n_hit"))
    named = hits.where("item is not null").select("digest", "item").distinct().groupBy("digest").agg(F.sort_array(F.collect_list("item")).alias("items"))
    out = covered.join(named, "digest", "left")
    items = F.coalesce("items", F.array().cast("array<string>"))
    return durable(out.select("digest", "n_hit", F.size(items).cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256")))


def _broadcasts(df: DataFrame) -> bool:
    return df._jdf.queryExecution().logical().getClass().getSimpleName() == "ResolvedHint"


def op8_decontaminate(spark, sf_dir: str) -> DataFrame:
    """Benchmark windows in every document, by whole texts; one row per document.

    Null and empty texts have no words and are clean, and so is every document
    if the benchmark is empty; repeated rows and null ids each come back.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text")
    return mark(docs, benchmark).drop("text")


def mark(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """The documents (id, text) with n_words, n_hit, n_items, items_sha256 and contaminated."""
    found = contamination(docs, benchmark, text)
    words = F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")
    placed = docs.withColumn("n_words", words).withColumn("digest", digest(text))
    out = placed.join(small_side(found), "digest", "left").drop("digest")
    out = out.withColumn("n_hit", F.coalesce("n_hit", F.lit(0))).withColumn("n_items", F.coalesce("n_items", F.lit(0)))
    return out.withColumn("items_sha256", F.coalesce("items_sha256", F.sha2(F.lit(""), 256))).withColumn("contaminated", F.col("n_hit") > 0)


SQL_OP8 = r"""
WITH dw AS (
  SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws
  FROM documents),
bw AS (
  SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws
  FROM benchmark),
win AS (
  SELECT DISTINCT item_id, least(len(ws), 10) AS n, array_to_string(ws[k : k + least(len(ws), 10) - 1], ' ') AS w
  FROM (SELECT *, unnest(range(1, len(ws) - least(len(ws), 10) + 2)) AS k FROM bw WHERE len(ws) > 0)),
lens AS (SELECT DISTINCT n FROM win),
dwin AS (
  SELECT doc_id, n, k, array_to_string(ws[k : k + n - 1], ' ') AS w
  FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS k FROM dw, lens WHERE len(ws) >= n)),
hit AS (SELECT d.doc_id, d.n, d.k, i.item_id FROM dwin d JOIN win i ON d.w = i.w AND d.n = i.n),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM hit) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, sha256(string_agg(i, ',' ORDER BY i)) AS items_sha256
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM hit) GROUP BY doc_id)
SELECT dw.doc_id, coalesce(len(ws), 0)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       coalesce(items_sha256, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN words ON dw.doc_id = words.doc_id LEFT JOIN items ON dw.doc_id = items.doc_id
"""


def drop_contaminated(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents that hold a benchmark window go, the others keep their columns.

    Null and empty texts stay. All copies of a contaminated text go. Further
    columns pass through, whatever their names; an empty table stays empty.
    """
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text")
    found = contamination(docs.select("text"), benchmark).select(F.col("digest").alias("hit"))
    packed = docs.select(F.struct("*").alias("row"), digest().alias("digest"))
    return packed.join(small_side(found), F.col("digest") == F.col("hit"), "left_anti").select("row.*")
