"""Near copies by the exact Jaccard similarity of their word shingles.

Shingles are ordered, rare ones first. Two sets of similarity t share a shingle
among the first n - ceil(t n) + 1 of each. Where few texts share one, each pair
of them is a candidate unless its places in the order, or counts of its shingles
by buckets, rule it out; where many do, they are chained by size. Neighbours by
size come first, so that of the other pairs only those are made whose texts the
neighbours leave in different components. A component of all holds all similar
texts of its members, and its sets meet in one task, which compares them
exactly. Nothing is estimated: places and counts are true bounds, and all texts
are counted for the order.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import SortedTable, byte_table, durable, gathered, mix64, small_side, words_of
from sevenfold.llm.graph import connected_components, local_components

WIDTH = 5
SIMILARITY = 0.8
#: Words are what whitespace leaves.
SPACED = byte_table([(0x00, 0x08), (0x0E, 0x1F), (0x21, 0xFF)])
#: Common shingles that are told apart; the rest counts as equally rare.
COMMON = 500_000
#: Bytes of text whose shingles are counted as one block.
BLOCK_BYTES = 16 << 20
#: Shingles that a task holds before it sums equal ones.
FLUSH = 500_000
#: Up to this many texts of a shingle are paired, more are chained.
PAIRED = 48
#: Shingles before one in a text's order that go along with it.
BACK = 2
#: Buckets of the counts by which a pair is ruled out.
BUCKETS = 512
_STEP = np.uint64(0xD6E8FEB86659FD93)


def shingle_sets(texts, width: int = WIDTH):
    """Yield (numbers of the texts, place of each shingle in them, shingle), by place and shingle, distinct.

    A text of fewer words than ``width`` has one shingle of them all, an empty one a shingle of none.
    """
    for numbers, offsets, data in gathered(texts):
        _, starts, _, hashes = words_of(data, SPACED)
        word = hashes[0]
        doc = np.searchsorted(offsets, starts, side="right") - 1
        count = np.bincount(doc, minlength=len(offsets))
        first = np.cumsum(count) - count
        at = np.flatnonzero(doc[: len(doc) - width + 1] == doc[width - 1 :]) if len(doc) >= width else np.zeros(0, dtype=np.int64)
        places, values = [doc[at]], [_joined(word, at, width)]
        for c in range(width):
            short = np.flatnonzero(count == c)
            places.append(short)
            values.append(_joined(word, first[short], c))
        place, value = np.concatenate(places), np.concatenate(values)
        order = np.lexsort((value, place))
        place, value = place[order], value[order]
        new = np.ones(len(place), dtype=bool)
        new[1:] = (place[1:] != place[:-1]) | (value[1:] != value[:-1])
        yield np.array(numbers), place[new], value[new]


def _joined(word: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the ``n`` words from each of ``at``."""
    h = np.full(len(at), n, dtype=np.uint64)
    for k in range(n):
        h = mix64(h * _STEP + word[at + k])
    return h


def prefix_length(n: np.ndarray, similarity: float) -> np.ndarray:
    """Shingles of a set of ``n`` of which a similar set shares one."""
    return n - np.ceil(similarity * n - 1e-9).astype(np.int64) + 1


def common_shingles(docs: DataFrame, width: int) -> tuple[np.ndarray, np.ndarray]:
    """The shingles that most texts of (h, text) have, sorted, and how many texts have each; three at least.

    All texts are counted. Counts go by levels of a ninth; as many whole levels come
    back, from the top, as hold ``COMMON`` shingles at most. Shingles go to the tasks in blocks by their high bits,
    equal ones summed before; a task holds one block's shingles at a time.
    """
    held = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = 1 << max(tasks - 1, held // BLOCK_BYTES).bit_length()
    shift = np.uint64(65 - blocks.bit_length())

    def summed(values: list[np.ndarray]):
        value, n = np.unique(np.concatenate(values), return_counts=True)
        block = (value >> shift).astype(np.int64) if blocks > 1 else np.zeros(len(value), dtype=np.int64)
        edge = np.flatnonzero(np.diff(block, prepend=-1))
        ends = np.append(edge[1:], len(value))
        # most occur once and need no count
        rows = []
        for k, e in zip(edge.tolist(), ends.tolist(), strict=True):
            v, c = value[k:e], n[k:e]
            rows.append((int(block[k]), v[c == 1].tobytes(), v[c > 1].tobytes(), c[c > 1].astype(np.int64).tobytes()))
        return pd.DataFrame(rows, columns=["block", "once", "more", "counts"])

    def blocked(batches):
        values, size = [], 0
        for b in batches:
            for _, _, value in shingle_sets(b["text"], width):
                values.append(value)
                size += len(value)
                if size > FLUSH:
                    yield summed(values)
                    values, size = [], 0
        if size:
            yield summed(values)

    def counted(batches):
        def done(once, more, counts):
            values = np.frombuffer(b"".join(once + more), dtype=np.uint64)
            counts = np.frombuffer(b"".join(counts), dtype=np.int64)
            order = np.argsort(values, kind="stable")
            n = np.concatenate((np.ones(len(values) - len(counts), dtype=np.int64), counts))[order]
            values = values[order]
            first = np.flatnonzero(np.concatenate(([True], values[1:] != values[:-1])))
            n = np.add.reduceat(n, first)
            return pd.DataFrame({"s": values[first][n > 2].view(np.int64), "n": n[n > 2]})

        last, got = None, ([], [], [])
        for b in batches:
            for block, *parts in zip(b["block"].tolist(), b["once"], b["more"], b["counts"], strict=True):
                if block != last and last is not None:
                    yield done(*got)
                    got = ([], [], [])
                last = block
                for held, part in zip(got, parts, strict=True):
                    held.append(part)
        if last is not None:
            yield done(*got)

    blocks_of = docs.mapInPandas(blocked, "block long, once binary, more binary, counts binary")
    often = blocks_of.repartition(tasks, "block").sortWithinPartitions("block").mapInPandas(counted, "s long, n long")
    often = durable(often.withColumn("level", F.floor(8 * F.log2("n")).cast("int")))
    least, total = 1 << 30, 0
    for level, size in sorted(often.groupBy("level").count().collect(), reverse=True):
        total += size
        if total > COMMON:
            break
        least = level
    found = often.where(F.col("level") >= least).select("s", "n").toPandas()
    value = found["s"].to_numpy(dtype=np.int64).view(np.uint64)
    order = np.argsort(value)
    return value[order], found["n"].to_numpy(dtype=np.int64)[order]


@dataclass
class _Postings:
    """Postings of several shingles in order of shingle, size and text; those that stand alone are left out."""

    s: np.ndarray
    h: np.ndarray
    n: np.ndarray
    r: np.ndarray
    many: np.ndarray
    before: list[np.ndarray]
    rest: list[np.ndarray]

    @classmethod
    def read(cls, batches, *further: str):
        """Of all batches; ``further`` names columns that go along. None if they are empty."""
        columns = ("s", "h", "n", "r", *(f"p{k}" for k in range(BACK)), *further)
        got = [tuple(b[c].to_numpy() for c in columns) for b in batches if len(b)]
        if not got:
            return None
        held = [np.concatenate(x) for x in zip(*got, strict=True)]
        del got
        order = np.lexsort((held[1], held[2], held[0]))
        held = [x[order] for x in held]
        new = np.flatnonzero(np.concatenate(([True], held[0][1:] != held[0][:-1])))
        length = np.diff(np.append(new, len(held[0])))
        many = np.repeat(length, length)
        s, h, n, r, *more = (x[many > 1] for x in held)
        return cls(s, h, n, r, many[many > 1], more[:BACK], more[BACK:])

    def near(self, step: int, similarity: float) -> np.ndarray:
        """Which postings share the shingle with the one ``step`` further, of a text of similar size."""
        x, y = slice(None, -step), slice(step, None)
        return (self.s[x] == self.s[y]) & (self.h[x] != self.h[y]) & (self.n[x] >= similarity * self.n[y] - 1e-9)

    def pairs(self, step: int, similarity: float) -> np.ndarray:
        """Numbers of those of a shingle of few texts that form a pair which places don't rule out and didn't meet before."""
        x, y = slice(None, -step), slice(step, None)
        # a pair is kept at the first shingle it shares, if at all
        most = np.minimum(self.n[x] - self.r[x], self.n[y] - self.r[y])
        most = most >= similarity / (1 + similarity) * (self.n[x].astype(np.int64) + self.n[y]) - 1e-9
        at = np.flatnonzero(self.near(step, similarity) & (self.many[x] <= PAIRED) & most)
        return at[~_met_before(self.before, self.r, at, at + step)]

    def table(self, at: np.ndarray, step: int) -> dict[str, np.ndarray]:
        a, b = self.h[at], self.h[at + step]
        return {"a": np.maximum(a, b), "b": np.minimum(a, b)}


_PLACES = "n int, r int" + "".join(f", p{k} long" for k in range(BACK))


def postings(docs: DataFrame, common: tuple[np.ndarray, np.ndarray], width: int, similarity: float) -> DataFrame:
    """(s, h, n, r, p0, ...): prefix shingles of texts of (h, text), with size of the set, place in its order and shingles before."""
    told = docs.sparkSession.sparkContext.broadcast((SortedTable(common[0]), common[1]))

    def listed(batches):
        table, often = told.value
        for b in batches:
            h = b["h"].to_numpy(dtype=np.int64)
            for numbers, place, value in shingle_sets(b["text"], width):
                level = np.zeros(len(value), dtype=np.int64)
                which, at = table.find(value)
                level[which] = often[at]
                order = np.lexsort((value, level, place))
                place, value = place[order], value[order]
                n = np.bincount(place, minlength=len(numbers))
                rank = np.arange(len(place)) - (np.cumsum(n) - n)[place]
                use = rank < prefix_length(n, similarity)[place]
                before = {f"p{k}": np.roll(value, k + 1)[use].view(np.int64) for k in range(BACK)}
                yield pd.DataFrame({"s": value[use].view(np.int64), "h": h[numbers[place[use]]], "n": n[place[use]].astype(np.int32), "r": rank[use].astype(np.int32)} | before)

    return docs.mapInPandas(listed, f"s long, h long, {_PLACES}")


def neighbours(found: DataFrame, similarity: float) -> DataFrame:
    """(kind, a, b, s, places) from postings: what a shingle's texts in order of size say of each other.

    In order of size, texts between two of similar size are of similar size too.
    ``chain``: a and b are next to each other at a common shingle and go together
    without comparison. ``pair``: next to each other at another shingle, and may be
    similar. ``posting``: text a at a shingle that has further pairs, for ``across``.
    """

    def linked(batches):
        got = _Postings.read(batches)
        if got is None or len(got.s) < 2:
            return
        at = np.flatnonzero(got.near(1, similarity) & (got.many[:-1] > PAIRED))
        none = {"s": 0, "n": 0, "r": 0} | {f"p{k}": 0 for k in range(BACK)}
        for kind, places in (("chain", at), ("pair", got.pairs(1, similarity))):
            if len(places):
                yield pd.DataFrame({"kind": kind} | got.table(places, 1) | none).drop_duplicates()
        open_ = np.zeros(len(got.s), dtype=bool)
        for step in range(2, min(PAIRED, len(got.s))):
            at = got.pairs(step, similarity)
            open_[at] = open_[at + step] = True
        if open_.any():
            places = {"s": got.s[open_], "n": got.n[open_], "r": got.r[open_]} | {f"p{k}": x[open_] for k, x in enumerate(got.before)}
            yield pd.DataFrame({"kind": "posting", "a": got.h[open_], "b": 0} | places)

    parts = int(found.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return found.repartition(parts, "s").mapInPandas(linked, f"kind string, a long, b long, s long, {_PLACES}")


def across(found: DataFrame, roots: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) of the postings of ``neighbours`` whose texts have different roots among (v, root)."""

    def linked(batches):
        got = _Postings.read(batches, "root")
        if got is None:
            return
        root = got.rest[0]
        for step in range(1, min(PAIRED, len(got.s))):
            at = got.pairs(step, similarity)
            at = at[root[at] != root[at + step]]
            if len(at):
                yield pd.DataFrame(got.table(at, step)).drop_duplicates()

    parts = int(found.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    known = found.where("kind = 'posting'").join(roots, found["a"] == roots["v"], "left")
    known = known.select("s", F.col("a").alias("h"), "n", "r", *(f"p{k}" for k in range(BACK)), F.coalesce("root", "a").alias("root"))
    return known.repartition(parts, "s").mapInPandas(linked, "a long, b long")


def candidate_components(docs: DataFrame, common: tuple[np.ndarray, np.ndarray], width: int, similarity: float) -> DataFrame:
    """(v, root) of texts of (h, text): similar ones have one root, whose members need comparison still."""
    counts = durable(counts_of(docs, width))
    found = durable(neighbours(postings(docs, common, width, similarity), similarity))
    pairs = possible(found.where("kind = 'pair'").select("a", "b").distinct(), counts, similarity)
    first = durable(connected_components(found.where("kind = 'chain'").select("a", "b").unionByName(pairs)))
    further = durable(possible(across(found, small_side(first), similarity).distinct(), counts, similarity))
    if further.isEmpty():
        return first
    return connected_components(first.toDF("a", "b").unionByName(further))


def _met_before(before: list[np.ndarray], rank: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Whether postings ``x`` and ``y`` of one shingle share one of those just before it, where their texts have met already."""
    met = np.zeros(len(x), dtype=bool)
    for i, p in enumerate(before):
        for j, q in enumerate(before):
            met |= (p[x] == q[y]) & (rank[x] > i) & (rank[y] > j)
    return met


def counts_of(docs: DataFrame, width: int) -> DataFrame:
    """(h, n, counts): size of each text's set, and its shingles by bucket, 255 at most."""

    def counted(batches):
        for b in batches:
            h = b["h"].to_numpy(dtype=np.int64)
            for numbers, place, value in shingle_sets(b["text"], width):
                cell = place * BUCKETS + (value % np.uint64(BUCKETS)).astype(np.int64)
                counts = np.minimum(np.bincount(cell, minlength=len(numbers) * BUCKETS), 255).astype(np.uint8).reshape(-1, BUCKETS)
                yield pd.DataFrame({"h": h[numbers], "n": np.bincount(place, minlength=len(numbers)), "counts": [c.tobytes() for c in counts]})

    return docs.mapInPandas(counted, "h long, n long, counts binary").dropDuplicates(["h"])


def possible(pairs: DataFrame, counts: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) whose counts differ by no more than sets of the similarity can."""

    @F.pandas_udf("long")
    def apart(x: pd.Series, y: pd.Series) -> pd.Series:
        x, y = (np.frombuffer(b"".join(c), dtype=np.uint8).reshape(-1, BUCKETS).astype(np.int16) for c in (x, y))
        return pd.Series(np.abs(x - y).sum(axis=1, dtype=np.int64))

    for side in ("a", "b"):
        pairs = pairs.join(counts.select(F.col("h").alias(side), F.col("n").alias(f"n_{side}"), F.col("counts").alias(f"counts_{side}")), side)
    most = (F.col("n_a") + F.col("n_b")) * (1 - similarity) / (1 + similarity) + 1e-6
    return pairs.where(apart("counts_a", "counts_b") <= most).select("a", "b")


def _overlap(x: np.ndarray, y: np.ndarray) -> int:
    both = np.concatenate((x, y))
    both.sort()
    return int((both[1:] == both[:-1]).sum())


def similar_components(sets: list[np.ndarray], similarity: float = SIMILARITY) -> np.ndarray:
    """Component label of each of ``sets`` (sorted, distinct) under links of at least ``similarity``.

    A set is first compared with the one before it in order of size that shares
    its rarest shingle. Of what is then apart, all sets outside the largest
    component are compared with all others.
    """
    m = len(sets)
    size = np.array([len(s) for s in sets])
    if m == 2:
        o = _overlap(*sets)
        return np.array([0, 0 if o / (size.sum() - o) >= similarity else 1])
    owner = np.repeat(np.arange(m), size)
    _, token = np.unique(np.concatenate(sets), return_inverse=True)
    start = np.cumsum(size) - size
    df = np.bincount(token)
    by_token = np.argsort(token, kind="stable")
    posting, first = owner[by_token], np.cumsum(df) - df
    a, b, last = [], [], {}
    for x in np.argsort(size, kind="stable").tolist():
        own = token[start[x] : start[x] + size[x]]
        own = own[df[own] > 1]
        for t in own[np.argsort(df[own], kind="stable")[:2]].tolist():
            y = last.get(t)
            last[t] = x
            if y is not None:
                o = _overlap(sets[x], sets[y])
                if o / (size[x] + size[y] - o) >= similarity:
                    a.append(x)
                    b.append(y)
    label = local_components(m, np.array(a, dtype=np.int64), np.array(b, dtype=np.int64))
    for x in np.flatnonzero(label != np.bincount(label).argmax()).tolist():
        own = token[start[x] : start[x] + size[x]]
        n = df[own]
        all_of = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(first[own], n)
        o = np.bincount(posting[all_of], minlength=m)
        near = np.flatnonzero((o > 0) & (o / (size[x] + size - o) >= similarity))
        a.extend([x] * len(near))
        b.extend(near.tolist())
    return local_components(m, np.array(a, dtype=np.int64), np.array(b, dtype=np.int64), label)


def near_copies(docs: DataFrame, width: int = WIDTH, similarity: float = SIMILARITY) -> DataFrame:
    """(h, root) for each text of (h, text) that has a near copy; ``h`` tells texts apart.

    Links close transitively; the root is some text of the group. The sets of a
    component of the candidates must fit the memory of one task.
    """
    common = common_shingles(docs, width)
    parts = candidate_components(docs, common, width, similarity)

    def listed(batches):
        for b in batches:
            h, root = b["h"].to_numpy(dtype=np.int64), b["root"].to_numpy(dtype=np.int64)
            for numbers, place, value in shingle_sets(b["text"], width):
                cut = np.flatnonzero(place[1:] != place[:-1]) + 1
                yield pd.DataFrame({"root": root[numbers], "h": h[numbers], "s": np.split(value.view(np.int64), cut)})

    def compared(batches):
        def done(root, h, sets):
            if len(h) > 1:
                # shingles come sorted as unsigned
                label = similar_components(sets, similarity)
                many = np.bincount(label, minlength=len(h))[label] > 1
                if many.any():
                    h = np.array(h, dtype=np.int64)
                    yield pd.DataFrame({"h": h[many], "root": h[label[many]]})

        # texts come by root and h, so that one component is held at a time
        last, h, sets = None, [], []
        for b in batches:
            for root, own, s in zip(b["root"].tolist(), b["h"].tolist(), b["s"], strict=True):
                if root != last:
                    yield from done(last, h, sets)
                    last, h, sets = root, [], []
                if not h or own != h[-1]:
                    h.append(own)
                    sets.append(np.array(s, dtype=np.int64).view(np.uint64))
        yield from done(last, h, sets)

    members = parts.unionByName(parts.select(F.col("root").alias("v"), "root").distinct())
    members = small_side(durable(members))
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sets = docs.join(members, docs["h"] == members["v"]).select("h", "text", "root").mapInPandas(listed, "root long, h long, s array<long>")
    return sets.repartition(tasks, "root").sortWithinPartitions("root", "h").mapInPandas(compared, "h long, root long")
