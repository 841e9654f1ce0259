"""Exact deduplication with counting quotient filters.

A fingerprint's high bits are its quotient, the low bits its remainder. Every
partition builds filters for blocks of quotients: slots that hold the remainders
of each quotient as a sorted run, with three bits of metadata a slot (quotient
occupied, run ends here, slot goes on with a counter) and counters that take
slots only where a fingerprint repeats. The filters of a block merge without
loss by merging the sorted remainders and adding the counters. Fingerprints with
a count above one go to a comparison of the whole texts; all others are unique.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sevenfold.llm.common import durable, small_side

#: Share of a filter's slots that is filled at most.
LOAD = 0.9
#: Fingerprints that a partition holds before it emits filters.
FLUSH_ROWS = 4_000_000
#: Fingerprints aimed at for a block; sets the number of blocks by the count of rows.
BLOCK_ROWS = 250_000


def _pack_bits(values: np.ndarray, bits: int) -> bytes:
    """The lowest ``bits`` of each value, one after another."""
    if not bits or not len(values):
        return b""
    return np.packbits(np.unpackbits(values.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)[:, 64 - bits :]).tobytes()


def _unpack_bits(data: np.ndarray, n: int, bits: int) -> np.ndarray:
    if not bits or not n:
        return np.zeros(n, dtype=np.uint64)
    wide = np.zeros((n, 64), dtype=np.uint8)
    wide[:, 64 - bits :] = np.unpackbits(data, count=n * bits).reshape(n, bits)
    return np.packbits(wide, axis=1).view(">u8").ravel().astype(np.uint64)


class CountingQuotientFilter:
    """The filter of one block of fingerprints, which share their highest ``block_bits`` bits.

    There are 2**``q`` quotients. A run's first slot is its quotient's or, if an
    earlier run is still there, the next free one; runs past the last quotient
    use slots beyond it. A fingerprint takes a slot with its remainder; one that
    occurs c > 1 times is followed by slots with the digits of c - 1 in base
    2**r, r being the remainder's bits, marked as counters.
    """

    def __init__(self, block_bits: int, q: int, remainders: np.ndarray, occupied: np.ndarray, ends: np.ndarray, counter: np.ndarray):
        self.block_bits, self.q, self.r = block_bits, q, 64 - block_bits - q
        self.remainders, self.occupied, self.ends, self.counter = remainders, occupied, ends, counter

    @classmethod
    def of(cls, fingerprints: np.ndarray, counts: np.ndarray, block_bits: int) -> CountingQuotientFilter:
        """From sorted distinct fingerprints of one block and how often each occurs."""
        digits = np.zeros(len(fingerprints), dtype=np.int64)
        more = counts.astype(np.uint64) - np.uint64(1)
        q = max(1, math.ceil(math.log2(max(1, len(fingerprints)) / LOAD)))
        r = np.uint64(64 - block_bits - q)
        left = more.copy()
        while left.any():
            digits[left > 0] += 1
            left >>= r
        low = fingerprints & np.uint64((1 << (64 - block_bits)) - 1)
        quotient, remainder = (low >> r).astype(np.int64), low & np.uint64((1 << int(r)) - 1)
        length = 1 + digits
        before = np.cumsum(length) - length
        # a run begins at its quotient, or where the runs before it have ended
        slot = before + np.maximum.accumulate(quotient - before) if len(quotient) else before
        size = max(1 << q, int(slot[-1] + length[-1]) if len(slot) else 0)
        cells, counter, ends = np.zeros(size, dtype=np.uint64), np.zeros(size, dtype=bool), np.zeros(size, dtype=bool)
        cells[slot] = remainder
        for k in range(int(digits.max(initial=0))):
            has = digits > k
            at = slot[has] + 1 + k
            cells[at] = (more[has] >> np.uint64(k * int(r))) & np.uint64((1 << int(r)) - 1)
            counter[at] = True
        last = np.flatnonzero(np.append(quotient[1:] != quotient[:-1], True)) if len(quotient) else np.zeros(0, dtype=np.int64)
        ends[slot[last] + length[last] - 1] = True
        occupied = np.zeros(1 << q, dtype=bool)
        occupied[quotient] = True
        return cls(block_bits, q, cells, occupied, ends, counter)

    def entries(self) -> tuple[np.ndarray, np.ndarray]:
        """The fingerprints below the block's bits, in order, and their counts."""
        quotients, stop = np.flatnonzero(self.occupied), np.flatnonzero(self.ends)
        begin = np.maximum(quotients, np.append(0, stop[:-1] + 1)) if len(stop) else stop
        length = stop - begin + 1
        run = np.repeat(np.arange(len(stop)), length)
        slot = np.arange(len(run)) - np.repeat(np.cumsum(length) - length, length) + begin[run]
        own = ~self.counter[slot]
        first = slot[own]
        keys = (quotients[run[own]].astype(np.uint64) << np.uint64(self.r)) | self.remainders[first]
        counts = np.ones(len(first), dtype=np.uint64)
        at = np.flatnonzero(~own)
        entry = np.cumsum(own)[at] - 1
        place = slot[at] - first[entry] - 1
        np.add.at(counts, entry, self.remainders[slot[at]] << (place * self.r).astype(np.uint64))
        return keys, counts

    def pack(self) -> bytes:
        """Quotient bits and slots, then the bits of occupied, run ends, counters and remainders; empty slots cost as much as full ones."""
        n = len(self.remainders)
        head = np.array([self.q, n], dtype="<u4").tobytes()
        return head + b"".join(np.packbits(x).tobytes() for x in (self.occupied, self.ends, self.counter)) + _pack_bits(self.remainders, self.r)

    @classmethod
    def unpack(cls, data: bytes, block_bits: int) -> CountingQuotientFilter:
        q, n = (int(x) for x in np.frombuffer(data, "<u4", 2))
        raw, at, flags = np.frombuffer(data, np.uint8), 8, []
        for size in (1 << q, n, n):
            flags.append(np.unpackbits(raw[at : at + (size + 7) // 8], count=size).astype(bool))
            at += (size + 7) // 8
        return cls(block_bits, q, _unpack_bits(raw[at:], n, 64 - block_bits - q), *flags)


def merge_filters(filters: list[CountingQuotientFilter]) -> CountingQuotientFilter:
    """Merge by sorted quotients and remainders; equal ones add their counters. Nothing is lost."""
    found = [f.entries() for f in filters]
    keys, counts = (np.concatenate(x) for x in zip(*found, strict=True))
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, dtype=np.int64)
    return CountingQuotientFilter.of(keys[first], np.add.reduceat(counts, first) if len(first) else counts, filters[0].block_bits)


def repeated_fingerprints(prints: DataFrame, column: str = "fp") -> DataFrame:
    """(fp, n) of the 64-bit values that occur more than once."""
    rows = prints.count()
    bits = min(20, max(6, math.ceil(math.log2(max(1, rows / BLOCK_ROWS)))))

    def build(batches):
        held, size = [], 0

        def flush():
            keys, counts = np.unique(np.concatenate(held), return_counts=True)
            block = (keys >> np.uint64(64 - bits)).astype(np.int64)
            cut = np.flatnonzero(np.concatenate(([True], block[1:] != block[:-1], [True])))
            return pd.DataFrame([(int(block[a]), CountingQuotientFilter.of(keys[a:b], counts[a:b], bits).pack()) for a, b in zip(cut[:-1], cut[1:], strict=True)], columns=["block", "filter"])

        for batch in batches:
            if len(batch):
                held.append(batch[column].to_numpy(dtype=np.int64).view(np.uint64))
                size += len(batch)
            if size >= FLUSH_ROWS:
                yield flush()
                held, size = [], 0
        if held:
            yield flush()

    def merged(batch: pd.DataFrame) -> pd.DataFrame:
        one = merge_filters([CountingQuotientFilter.unpack(x, bits) for x in batch["filter"]])
        keys, counts = one.entries()
        many = counts > 1
        high = np.uint64(int(batch["block"].iloc[0])) << np.uint64(64 - bits)
        return pd.DataFrame({"fp": (keys[many] | high).view(np.int64), "n": counts[many].astype(np.int64)})

    return prints.select(column).mapInPandas(build, "block long, filter binary").groupBy("block").applyInPandas(merged, "fp long, n long")


def duplicate_groups(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(fp, sha, keep_id, n, tied) of every set of two or more equal texts, checkpointed.

    ``tied``: several rows carry the largest key. Texts are compared whole; the
    comparison aggregates copies before it shuffles, so that a group with a third
    of all rows sends one row a task.
    """
    value = F.coalesce(F.col(text), F.lit(""))
    base = docs.select(F.col(key).alias("id"), value.alias("t"), F.xxhash64(value).alias("fp"))
    repeated = durable(repeated_fingerprints(base.select("fp")).select("fp"))
    at_risk = base.join(small_side(repeated), "fp", "left_semi")
    groups = at_risk.groupBy("fp", "t").agg(F.max("id").alias("keep_id"), F.count("*").alias("n")).where("n > 1")
    groups = durable(groups.select("fp", F.sha2("t", 256).alias("sha"), "keep_id", "n"))
    rows = base.join(small_side(groups.select("fp").distinct()), "fp", "left_semi").select("fp", "id", F.sha2("t", 256).alias("sha"))
    held = rows.join(small_side(groups), ["fp", "sha"]).where(F.col("id").eqNullSafe(F.col("keep_id"))).groupBy("fp", "sha").agg(F.count("*").alias("ties"))
    return durable(groups.join(small_side(durable(held)), ["fp", "sha"], "left").select("fp", "sha", "keep_id", "n", (F.col("ties") > 1).alias("tied")))


def op4_exact_dedup(spark, sf_dir: str) -> DataFrame:
    """Which document stays of every set of equal texts; one row per document.

    Null counts as empty, so null and empty texts are one group. The row with the
    largest doc_id stays (nulls last); of rows that repeat id and text, one stays.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    groups = duplicate_groups(docs)
    value = F.coalesce(F.col("text"), F.lit(""))
    light = docs.select("doc_id", F.xxhash64(value).alias("fp"), F.sha2(value, 256).alias("text_sha256"))
    found = light.join(small_side(groups.withColumnRenamed("sha", "text_sha256")), ["fp", "text_sha256"], "left")
    kept = F.col("n").isNull() | F.col("doc_id").eqNullSafe(F.col("keep_id"))
    if groups.where("tied").limit(1).count():
        one = Window.partitionBy("fp", "text_sha256", "doc_id").orderBy("n")
        found = found.withColumn("turn", F.row_number().over(one))
        kept = kept & (~F.coalesce(F.col("tied"), F.lit(False)) | (F.col("turn") == 1))
    return found.select(
        "doc_id",
        F.when(F.col("n").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        kept.alias("kept"),
        "text_sha256",
    )


SQL_OP4 = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS n FROM d GROUP BY t)
SELECT d.doc_id, g.keep_id, g.n AS group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256
FROM d JOIN g ON d.t = g.t
"""


def drop_exact_copies(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of equal texts the row with the largest doc_id stays, whole.

    Null counts as empty. Null doc_ids are the smallest; of rows that repeat id
    and text one stays. Further columns pass through, whatever their names; an
    empty table stays empty.
    """
    groups = duplicate_groups(docs)
    value = F.coalesce(F.col("text"), F.lit(""))
    packed = docs.select(F.struct("*").alias("row"), F.col("doc_id").alias("id"), F.xxhash64(value).alias("fp"), F.sha2(value, 256).alias("sha"))
    found = packed.join(small_side(groups), ["fp", "sha"], "left")
    kept = found.where(F.col("n").isNull() | F.col("id").eqNullSafe(F.col("keep_id")))
    if groups.where("tied").limit(1).count():
        tied = F.coalesce(F.col("tied"), F.lit(False))
        kept = kept.where(~tied).unionByName(kept.where(tied).dropDuplicates(["fp", "sha"]))
    return kept.select("row.*")
