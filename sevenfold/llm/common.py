"""Shared helpers: durable checkpoints, checked broadcasts, vectorised word tables."""

from __future__ import annotations

import tempfile

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a side of a join may be broadcast; beyond it the join shuffles.
BROADCAST_ROWS = 1_000_000
#: Bytes of its values, as counted, up to which it may be.
BROADCAST_BYTES = 64 << 20

#: Bytes of text that are tokenised at once; longer texts go in pieces of this size.
PIECE_BYTES = 1 << 20

_MULTIPLIER = 0x9E3779B97F4A7C15 | 1


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``; in local mode a fresh one if none is set.

    On a cluster a folder of one machine would not do, so there it must be named.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="sevenfold-checkpoint-")
        sc.setCheckpointDir(named)
    elif not sc.getCheckpointDir():
        sc.setCheckpointDir(named)
    return named


def durable(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder: survives the loss of any executor."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def _value_bytes(df: DataFrame):
    """Column with about the bytes of a row's values: strings and arrays by their sizes, others 8 each."""
    total = F.lit(16)
    for name, kind in df.dtypes:
        if kind in ("string", "binary"):
            total = total + F.coalesce(F.octet_length(f"`{name}`"), F.lit(0))
        elif kind.startswith("array"):
            total = total + F.greatest(F.size(f"`{name}`"), F.lit(0)) * 16
        else:
            total = total + 8
    return total


def small_side(df: DataFrame, rows: int = BROADCAST_ROWS, size: int = BROADCAST_BYTES) -> DataFrame:
    """Mark ``df`` for broadcast only if it is counted to hold at most ``rows`` rows and ``size`` bytes.

    ``df`` should be checkpointed, as it is counted. Beyond the bounds it comes
    back unmarked, and Spark joins by shuffle with its skew handling.
    """
    n, held = df.agg(F.count("*"), F.sum(_value_bytes(df))).first()
    return F.broadcast(df) if n <= rows and (held or 0) <= size else df


def remainder_of_crc(column: str, modulus: int):
    """crc32 of the value's decimal text, modulo ``modulus``: the fixed folds."""
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(modulus))


# --------------------------------------------------------------------------- words
def byte_table(word_ranges) -> np.ndarray:
    """Boolean table over the 256 byte values, true in the given inclusive ranges."""
    table = np.zeros(256, dtype=bool)
    for low, high in word_ranges:
        table[low : high + 1] = True
    return table


#: Lower-cases the ASCII letters, leaves every other byte.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 0x20

#: Words of digits, ASCII letters and everything beyond ASCII.
ALNUM_WORD = byte_table([(0x30, 0x39), (0x61, 0x7A), (0x80, 0xFF)])


class _Powers:
    """Powers of an odd multiplier and of its inverse modulo 2**64, grown on demand."""

    forward = np.ones(1, dtype=np.uint64)
    backward = np.ones(1, dtype=np.uint64)

    @classmethod
    def upto(cls, n: int):
        if len(cls.forward) < n:
            size = 1 << (n - 1).bit_length()
            for name, base in (("forward", _MULTIPLIER), ("backward", pow(_MULTIPLIER, -1, 1 << 64))):
                steps = np.full(size, base, dtype=np.uint64)
                steps[0] = 1
                setattr(cls, name, np.multiply.accumulate(steps))
        return cls.forward, cls.backward


def mix64(h: np.ndarray) -> np.ndarray:
    """Finalise 64-bit hashes so that every bit depends on every other."""
    h = h ^ (h >> np.uint64(31))
    h = h * np.uint64(0x7FB5D329728EA185)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


def _cuts(data: np.ndarray, word: np.ndarray, limit: int) -> list[int]:
    """Ends of pieces of about ``limit`` bytes, none inside a word."""
    ends, at, n = [], 0, len(data)
    while n - at > limit:
        to = at + limit
        while to < n:
            gap = np.flatnonzero(~word[data[to : to + 4096]])
            if len(gap):
                to += int(gap[0])
                break
            to += 4096
        to = min(to, n)
        ends.append(to)
        at = to
    if at < n or not ends:
        ends.append(n)
    return ends


def words_of(data: bytes, word: np.ndarray = ALNUM_WORD, prefixes: tuple[int, ...] = (), limit: int = PIECE_BYTES):
    """Starts, ends and 64-bit hashes of the words in lower-cased ``data``.

    ``prefixes`` asks for further hash rows of each word's first bytes. Memory is
    bounded by ``limit`` for the temporaries, whatever the length of the text.
    """
    raw = LOWER[np.frombuffer(data, dtype=np.uint8)]
    starts, ends, hashes, at = [], [], [], 0
    for to in _cuts(raw, word, limit):
        piece = raw[at:to]
        inside = word[piece]
        edge = np.flatnonzero(np.diff(np.concatenate(([False], inside, [False])).view(np.int8)))
        s, e = edge[0::2], edge[1::2]
        if len(s):
            forward, backward = _Powers.upto(len(piece) + 1)
            total = np.zeros(len(piece) + 1, dtype=np.uint64)
            np.cumsum((piece.astype(np.uint64) + np.uint64(1)) * forward[: len(piece)], out=total[1:])
            rows = [mix64((total[e] - total[s]) * backward[s] + (e - s).astype(np.uint64))]
            for k in prefixes:
                stop = np.minimum(s + k, e)
                rows.append(mix64((total[stop] - total[s]) * backward[s] + np.uint64(k << 40)))
            starts.append(s + at)
            ends.append(e + at)
            hashes.append(np.stack(rows))
        at = to
    if not starts:
        empty = np.zeros(0, dtype=np.int64)
        return raw, empty, empty, np.zeros((1 + len(prefixes), 0), dtype=np.uint64)
    return raw, np.concatenate(starts), np.concatenate(ends), np.concatenate(hashes, axis=1)


def gathered(texts, limit: int = PIECE_BYTES):
    """Join the texts of a batch to buffers of about ``limit`` bytes.

    Yields (numbers of the texts, start of each, buffer). A longer text has a
    buffer of its own. Null counts as empty.
    """
    numbers, offsets, parts, size = [], [], [], 0
    for k, text in enumerate(texts):
        data = text.encode("utf-8", "surrogatepass") if isinstance(text, str) else b""
        if parts and size + len(data) > limit:
            yield numbers, np.array(offsets, dtype=np.int64), b" ".join(parts)
            numbers, offsets, parts, size = [], [], [], 0
        numbers.append(k)
        offsets.append(size)
        parts.append(data)
        size += len(data) + 1
    if parts:
        yield numbers, np.array(offsets, dtype=np.int64), b" ".join(parts)


def is_in_sorted(values: np.ndarray, table: np.ndarray):
    """Positions in the sorted ``table`` and a mask of the values that it holds."""
    if not len(table):
        return np.zeros(len(values), dtype=np.int64), np.zeros(len(values), dtype=bool)
    at = np.searchsorted(table, values)
    at[at == len(table)] = 0
    return at, table[at] == values


class SortedTable:
    """Sorted distinct hashes behind a table of their low bits.

    Most values that the table lacks end at one look-up; only the rest, at most
    about a sixteenth of them up to a million values, is searched for. The answer is exact.
    """

    def __init__(self, values: np.ndarray):
        self.values = values
        self.mask = np.uint64((1 << min(24, max(10, (16 * len(values)).bit_length()))) - 1)
        self._low = None  # made where it is used, so that it isn't shipped

    def find(self, values: np.ndarray):
        """Which of ``values`` are in the table, as numbers in order, and their places in it."""
        if self._low is None:
            self._low = np.zeros(int(self.mask) + 1, dtype=bool)
            self._low[self.values & self.mask] = True
        near = np.flatnonzero(self._low[values & self.mask])
        at, known = is_in_sorted(values[near], self.values)
        return near[known], at[known]
