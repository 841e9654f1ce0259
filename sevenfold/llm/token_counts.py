"""Exact histogram of encoded lengths, and what follows from its suffix sums."""

from __future__ import annotations

import base64
import os

import pandas as pd
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sevenfold.llm.common import durable

TOKENIZERS = "/opt/tokenizers"
VOCABULARY = "byte_bpe_50k.tiktoken"
#: The byte-pair pre-tokeniser of that vocabulary (fixed value).
PATTERN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Lengths of one block of the histogram, for sums in two steps.
BLOCK = 128
#: Runs of blanks from this length on are encoded as the one piece that they are: the
#: pattern's look-ahead steps back over a run, and a very long one overflows its stack.
LONG_BLANKS = 50_000
#: Cells of the grid of shares that finds the lengths of quantiles.
SHARE_CELLS = 1024

_blanks = regex.compile(rf"\s{{{LONG_BLANKS},}}+")
_encoders: dict[bytes, object] = {}


def _encoder(data: bytes):
    """One encoder per worker process."""
    import tiktoken

    name = data[:64] + str(len(data)).encode()
    if name not in _encoders:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, data.splitlines()) if a}
        _encoders[name] = tiktoken.Encoding("lengths", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
    return _encoders[name]


def encoded_length(encoder, text: str) -> int:
    """Tokens of a whole text, the same as its plain encoding has, whatever runs of blanks it holds.

    The pattern makes a run of blanks one piece, without its last blank if a
    word follows; so the text is cut there, and the piece is encoded alone.
    """
    if len(text) < LONG_BLANKS:
        return len(encoder.encode_ordinary(text))
    total, at = 0, 0
    for run in _blanks.finditer(text):
        stop = run.end() - (run.end() < len(text))
        total += len(encoder.encode_ordinary(text[at : run.start()])) + len(encoder._encode_single_piece(text[run.start() : stop]))
        at = stop
    return total + len(encoder.encode_ordinary(text[at:]))


def token_length(spark, folder: str = TOKENIZERS, vocabulary: str = VOCABULARY):
    """A column function: text -> tokens of the whole text; null counts as empty.

    The vocabulary file is read on the driver and goes out once per executor.
    Strings of special tokens are ordinary text.
    """
    with open(os.path.join(folder, vocabulary), "rb") as f:
        shipped = spark.sparkContext.broadcast(f.read())

    @F.pandas_udf("long")
    def count(texts: pd.Series) -> pd.Series:
        encoder = _encoder(shipped.value)
        return pd.Series([encoded_length(encoder, t) if isinstance(t, str) else 0 for t in texts], dtype="int64")

    return count


def histogram(lengths: DataFrame, column: str = "n_tokens") -> DataFrame:
    """One row per length with exact totals on either side; null lengths count as 0.

    ``docs_at_least`` and ``tokens_at_least`` are suffix sums. ``truncated_tokens``
    is the total when every document is cut to this length, ``rank`` the share of
    documents up to it. The histogram is summed block by block, then within blocks.
    """
    h = lengths.groupBy(F.coalesce(F.col(column), F.lit(0)).cast("long").alias("length")).agg(F.count("*").alias("n_docs"))
    h = durable(h)  # else each of its two uses would encode all texts
    h = h.withColumn("block", F.floor(F.col("length") / BLOCK)).withColumn("n_tokens", F.col("length") * F.col("n_docs"))
    after = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    blocks = h.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum("n_tokens").alias("t"))
    whole = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    blocks = blocks.select("block", *(F.coalesce(F.sum(c).over(after), F.lit(0)).alias(f"{c}_after") for c in "dt"), *(F.sum(c).over(whole).alias(f"{c}_all") for c in "dt"))
    inner = Window.partitionBy("block").orderBy(F.desc("length"))
    joined = h.withColumn("d_in", F.sum("n_docs").over(inner)).withColumn("t_in", F.sum("n_tokens").over(inner)).join(blocks, "block")
    least_d, least_t = F.col("d_after") + F.col("d_in"), F.col("t_after") + F.col("t_in")
    return joined.select(
        "length",
        "n_docs",
        "n_tokens",
        least_d.alias("docs_at_least"),
        least_t.alias("tokens_at_least"),
        (F.col("t_all") - least_t + F.col("length") * least_d).alias("truncated_tokens"),
        ((F.col("d_all") - least_d + F.col("n_docs")) / F.col("d_all")).alias("rank"),
    )


def truncated_total(hist: DataFrame, limits: list[int]) -> DataFrame:
    """(context_limit, tokens, docs_cut) for any limits, whether or not a document has that length.

    A limit is answered by the suffix sums at the least length that reaches it:
    what lies below stays whole, each document from there on gives the limit.
    That length is looked for in the limit's block, and if there is none, in the
    next block that has rows; both by equality. No row of ``hist`` is summed.
    """
    spark = hist.sparkSession
    wanted = spark.createDataFrame([(int(x),) for x in sorted(set(limits))], "context_limit long").withColumn("block", F.floor(F.col("context_limit") / BLOCK))
    suffix = F.struct("length", "n_docs", "docs_at_least", "tokens_at_least")
    rows = hist.withColumn("block", F.floor(F.col("length") / BLOCK))
    firsts = rows.groupBy("block").agg(F.min(suffix).alias("first"))
    # the first row of the nearest later block, for each block that has rows or a limit
    near = firsts.join(wanted.select("block").distinct(), "block", "full_outer")
    later = Window.orderBy("block").rowsBetween(1, Window.unboundedFollowing)
    near = near.select("block", F.first("first", ignorenulls=True).over(later).alias("later"))  # one row a block
    inner = rows.select("block", suffix.alias("own"))
    found = F.broadcast(wanted).join(near, "block").join(inner, "block", "left")
    reached = F.when(F.col("own.length") >= F.col("context_limit"), F.col("own"))
    found = found.groupBy("context_limit").agg(F.coalesce(F.min(reached), F.first("later")).alias("s"))
    all_tokens = hist.agg(F.max("tokens_at_least")).first()[0] or 0
    docs, tokens = (F.coalesce(F.col(f"s.{c}_at_least"), F.lit(0)) for c in ("docs", "tokens"))
    whole = F.when(F.col("s.length") == F.col("context_limit"), F.col("s.n_docs")).otherwise(0)
    return found.select("context_limit", (F.lit(all_tokens) - tokens + F.col("context_limit") * docs).alias("tokens"), (docs - whole).alias("docs_cut"))


def quantiles(hist: DataFrame, shares: list[float]) -> DataFrame:
    """(share, length): the least length that at least this share of documents doesn't exceed.

    A length covers the shares above those of the shorter lengths up to its rank;
    the suffix sums give both ends. Shares meet lengths by the cell of a grid.
    """
    wanted = hist.sparkSession.createDataFrame([(float(q),) for q in sorted(set(shares))], "share double").withColumn("cell", F.floor(F.col("share") * SHARE_CELLS))
    all_docs = hist.agg(F.max("docs_at_least")).first()[0] or 0
    low = (F.lit(all_docs) - F.col("docs_at_least")) / F.lit(all_docs)  # the rank of the next shorter length
    cell = lambda share: F.floor(share * SHARE_CELLS)
    cells = hist.select("length", "rank", F.explode(F.sequence(cell(low), cell(F.col("rank")))).alias("cell"))
    return F.broadcast(wanted).join(cells, "cell").where("share <= rank").groupBy("share").agg(F.min("length").alias("length"))


def op3_token_counts(spark, sf_dir: str) -> DataFrame:
    """Histogram of the encoded lengths of all documents, with suffix sums.

    One row for each length that occurs. A row answers every context limit above
    the next shorter length up to its own: the total is all tokens, less
    ``tokens_at_least``, plus the limit times ``docs_at_least``; ``rank`` answers
    the quantiles. An empty table gives no rows; null and empty texts have length
    0; very long texts are encoded whole; repeated rows count each.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("text")
    count = token_length(spark)
    return histogram(docs.select(count(F.col("text")).alias("n_tokens")))
