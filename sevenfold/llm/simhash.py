"""SimHash near-duplicates by a binary trie self-join.

Two 64-bit fingerprints with at most three differing bits agree in at least one
of four 16-bit segments. So each distinct fingerprint goes out four times, each
time rotated so that another segment comes first, and the tries of equal leading
segments are joined with themselves: pairs of nodes descend together, the bits
in which they differ add up, and a pair ends when they exceed the budget. Only
a spanning forest of the links leaves a task, never all pairs of a group.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import durable, small_side
from sevenfold.llm.graph import connected_components, local_components
from sevenfold.llm.shingles import SIMILARITY, WIDTH, near_copies

BUDGET = 3
SEGMENTS = 4
#: Node pairs that are expanded at once; the rest waits, which bounds memory.
FRONTIER = 1 << 20
#: A pair of nodes with at most this many pairs of leaves is compared leaf by leaf.
SMALL = 16
#: Rows aimed at for a task of the join.
TASK_ROWS = 500_000


# ---------------------------------------------------------------------- fingerprints
def _word_lists(data: bytes, limit: int = 4 << 20):
    """Words of lower-cased text, in lists of bounded size that overlap by two words."""
    data = data.lower()
    if len(data) <= limit:
        yield data.split()
        return
    at, carry = 0, []
    while at < len(data):
        to = min(len(data), at + limit)
        while to < len(data) and data[to] not in b" \t\n\r\x0b\x0c":
            to += 1
        words = carry + data[at:to].split()
        if to < len(data) and len(words) < 3:
            carry, at = words, to
            continue
        yield words
        carry, at = words[-2:], to


def fingerprint(text: str | None) -> int:
    """64-bit majority of the XXH64 values (seed 42) of the 3-word shingles; 0 without words."""
    ones, n = np.zeros(64, dtype=np.int64), 0
    digest = xxhash.xxh64_intdigest
    for words in _word_lists(text.encode("utf-8", "surrogatepass") if isinstance(text, str) else b""):
        if len(words) < 3:
            if not words or n:
                continue
            hashes = [digest(b" ".join(words), 42)]
        else:
            joined = b" ".join(words)
            size = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
            end = np.cumsum(size + 1) - 1
            hashes = [digest(joined[a:b], 42) for a, b in zip((end - size)[:-2].tolist(), end[2:].tolist(), strict=True)]
        n += len(hashes)
        for k in range(0, len(hashes), 65536):
            part = np.array(hashes[k : k + 65536], dtype="<u8")
            ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    value = 0
    for bit in np.flatnonzero(2 * ones > n) if n else ():
        value |= 1 << int(bit)
    return value


def _fingerprints(column):
    @F.pandas_udf("long")
    def prints(texts: pd.Series) -> pd.Series:
        return pd.Series(np.array([fingerprint(t) for t in texts], dtype=np.uint64).view(np.int64))

    return prints(column)


def simhash(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, fp long) for every row."""
    return docs.select(key, _fingerprints(F.col(text)).alias("fp"))


# ------------------------------------------------------------------------- trie join
def _ranges(lo: np.ndarray, n: np.ndarray):
    """All positions of the ranges [lo, lo+n), and the range of each."""
    which = np.repeat(np.arange(len(lo)), n)
    return np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + lo[which], which


def trie_links(values: np.ndarray, depth: int, budget: int, label: np.ndarray):
    """Yield (i, j) index arrays of links between sorted distinct ``values``.

    Values with equal first ``depth`` bits are joined. Pairs of nodes that lie
    wholly in one component of ``label`` are left out: they link nothing new.
    """
    n = len(values)
    if n < 2:
        return
    changes = np.concatenate(([0], np.cumsum(label[1:] != label[:-1])))
    top = values >> np.uint64(64 - depth) if depth else np.zeros(n, dtype=np.uint64)
    lo = np.flatnonzero(np.concatenate(([True], top[1:] != top[:-1])))
    hi = np.append(lo[1:], n)
    many = hi - lo > 1
    lo, hi = lo[many], hi[many]
    # (bits seen, differing bits, node a, node b); a node is a range of the sorted values
    stack = [(depth, np.zeros(len(lo), dtype=np.int64), lo, hi, lo, hi)]
    while stack:
        bit, diff, alo, ahi, blo, bhi = stack.pop()
        if len(diff) > FRONTIER:
            for k in range(0, len(diff), FRONTIER):
                stack.append((bit, *(x[k : k + FRONTIER] for x in (diff, alo, ahi, blo, bhi))))
            continue
        there = (diff <= budget) & (ahi > alo) & (bhi > blo)
        diff, alo, ahi, blo, bhi = (x[there] for x in (diff, alo, ahi, blo, bhi))
        same = alo == blo
        whole = (changes[ahi - 1] == changes[alo]) & (changes[bhi - 1] == changes[blo]) & (label[alo] == label[blo])
        live = ~whole & ~(same & (ahi - alo < 2))
        leaf = live & (((ahi - alo) * (bhi - blo) <= SMALL) | (bit >= 64))
        if leaf.any():
            a, which = _ranges(alo[leaf], (ahi - alo)[leaf])
            b, k = _ranges(blo[leaf][which], (bhi - blo)[leaf][which])
            a = a[k]
            ok = (a < b) & (np.bitwise_count(values[a] ^ values[b]) <= budget) & (label[a] != label[b])
            if ok.any():
                yield a[ok], b[ok]
        live &= ~leaf
        if not live.any():
            continue
        diff, alo, ahi, blo, bhi, same = (x[live] for x in (diff, alo, ahi, blo, bhi, same))
        one = np.concatenate(([0], np.cumsum((values >> np.uint64(63 - bit)) & np.uint64(1)))).astype(np.int64)
        amid, bmid = ahi - (one[ahi] - one[alo]), bhi - (one[bhi] - one[blo])
        cross = ~same
        stack.append((
            bit + 1,
            np.concatenate((diff, diff, diff + 1, diff[cross] + 1)),
            np.concatenate((alo, amid, alo, amid[cross])),
            np.concatenate((amid, ahi, amid, ahi[cross])),
            np.concatenate((blo, bmid, bmid, blo[cross])),
            np.concatenate((bmid, bhi, bhi, bmid[cross])),
        ))


def trie_components(values: np.ndarray, depth: int = 64 // SEGMENTS, budget: int = BUDGET) -> np.ndarray:
    """Component label (smallest index) of each of the sorted distinct ``values``.

    Small budgets come first, so that dense groups have merged before the wide
    search and its node pairs end early.
    """
    label = np.arange(len(values))
    for allowed in range(1, budget + 1):
        found = [(np.zeros(0, dtype=np.int64),) * 2]
        size = 0
        merged = label
        for i, j in trie_links(values, depth, allowed, label):
            found.append((i, j))
            size += len(i)
            if size > 4 * FRONTIER:
                merged = local_components(len(values), *map(np.concatenate, zip(*found, strict=True)), merged)
                found, size = found[:1], 0
        label = local_components(len(values), *map(np.concatenate, zip(*found, strict=True)), merged)
    return label


def near_links(prints: DataFrame, rows: int, parts: int) -> DataFrame:
    """Spanning links (a, b) between distinct fingerprints in column ``fp`` within the budget."""
    width = 64 // SEGMENTS

    def join(batches):
        got = [(b["s"].to_numpy(), b["fp"].to_numpy(dtype=np.int64).view(np.uint64)) for b in batches if len(b)]
        if not got:
            return
        segment, value = (np.concatenate(x) for x in zip(*got, strict=True))
        for s in range(SEGMENTS):
            own = value[segment == s]
            if len(own) < 2:
                continue
            turned = own if s == 0 else (own << np.uint64(s * width)) | (own >> np.uint64(64 - s * width))
            order = np.argsort(turned)
            own = own[order]
            label = trie_components(turned[order], width)
            moved = np.flatnonzero(label != np.arange(len(label)))
            if len(moved):
                yield pd.DataFrame({"a": own[moved].view(np.int64), "b": own[label[moved]].view(np.int64)})

    four = prints.select(F.explode(F.array(*(F.lit(s) for s in range(SEGMENTS)))).alias("s"), "fp")
    head = F.when(F.col("s") == 0, F.shiftrightunsigned("fp", 64 - width))
    for s in range(1, SEGMENTS):
        head = head.when(F.col("s") == s, F.shiftrightunsigned(F.shiftleft("fp", s * width), 64 - width))
    n = max(parts, SEGMENTS * rows // TASK_ROWS + 1)
    return four.withColumn("head", head).repartition(n, "s", "head").select("s", "fp").mapInPandas(join, "a long, b long")


def near_groups(prints: DataFrame, key: str = "doc_id") -> DataFrame:
    """(fp, component_id) for every distinct fingerprint of checkpointed (key, fp)."""
    spark = prints.sparkSession
    distinct = durable(prints.groupBy("fp").agg(F.min(key).alias("least")))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    links = near_links(distinct.select("fp"), distinct.count(), parts)
    roots = connected_components(links)
    members = roots.unionByName(roots.select(F.col("root").alias("v"), "root").distinct())
    least = members.join(distinct, members["v"] == distinct["fp"]).groupBy("root").agg(F.min("least").alias("component_id"))
    linked = durable(members.join(least, "root").select(F.col("v").alias("fp"), "component_id"))
    return distinct.join(small_side(linked), "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id"))


def op9_simhash(spark, sf_dir: str) -> DataFrame:
    """Fingerprint and near-duplicate component of every document.

    Null and empty texts have fingerprint zero and link like any other. Repeated
    rows each come back. The component id is the smallest doc_id reachable.
    """
    prints = durable(simhash(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    found = prints.join(near_groups(prints), "fp", "left")
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def similar_groups(grouped: DataFrame, near: DataFrame) -> DataFrame:
    """Links (a, b) between the groups ``s`` of (h, s) that hold texts of one group of checkpointed (h, root)."""
    own = grouped.select("h", "s").distinct()
    roots = durable(near.select(F.col("root").alias("h")).distinct())
    tops = durable(own.join(small_side(roots), "h").select(F.col("h").alias("root"), F.col("s").alias("b")))
    return own.join(small_side(near), "h").select("root", F.col("s").alias("a")).join(small_side(tops), "root").select("a", "b")


def drop_near_copies(spark, docs: DataFrame, sf_dir: str, width: int = WIDTH, similarity: float = SIMILARITY) -> DataFrame:
    """Pipeline stage: of each group the document with the smallest doc_id stays.

    Groups are op9's: fingerprints linked within the budget. An exact search follows, and
    joins groups that have texts whose shingles of ``width`` words are at least that similar
    (Jaccard), which three bits would mostly miss; no link of the fingerprints is lost by it.
    Rows that tie in id are told apart by a hash of their text; of whole repeats one stays.
    """
    mark = F.xxhash64(F.coalesce("text", F.lit("")))
    tagged = durable(docs.select(F.col("doc_id").alias("id"), mark.alias("h"), _fingerprints(F.col("text")).alias("fp")))
    grouped = durable(tagged.join(near_groups(tagged, "h"), "fp").select("id", "h", F.col("component_id").alias("s")))
    near = durable(near_copies(docs.select(mark.alias("h"), "text"), width, similarity))
    joined = small_side(durable(connected_components(similar_groups(grouped, near))))
    placed = grouped.join(joined, grouped["s"] == joined["v"], "left").select("id", "h", F.coalesce("root", "s").alias("component_id"))
    size = durable(placed.groupBy("component_id").agg(F.count("*").alias("n"), F.min(F.struct("id", "h")).alias("best")).where("n > 1"))
    members = placed.join(small_side(size), "component_id")
    gone = durable(members.where(~F.struct("id", "h").eqNullSafe(F.col("best"))).select("id", "h").distinct())
    packed = docs.select(F.struct("*").alias("row"), F.col("doc_id").alias("id"), mark.alias("h"))
    side = small_side(gone)
    kept = packed.join(side, packed["id"].eqNullSafe(side["id"]) & (packed["h"] == side["h"]), "left_anti")
    repeats = tagged.groupBy("id", "h").count().where("count > 1").limit(1).count()
    return (kept.dropDuplicates(["id", "h"]) if repeats else kept).select("row.*")
