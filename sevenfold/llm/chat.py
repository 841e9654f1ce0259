"""Minimum-cost role repair of conversations.

The legal conversations are those of a small automaton: an optional system turn,
then user and assistant in turn, the assistant last. Every given turn may keep
its role, merge with the message before it, be relabelled, or be preceded by
empty turns. Dynamic programming over the automaton's states finds the cheapest
repair. A turn's effect is a min-plus matrix over the states, and such matrices
compose; so long conversations are cut to chunks that are solved side by side,
and one that spans many partitions is repaired part by part, with only the
parts' 4 x 4 matrices between them.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import durable

#: States by the role of the last message; 0 is the beginning. As a given role, 0 is an unknown one.
START, SYSTEM, USER, ASSISTANT = range(4)
ROLES = {"system": SYSTEM, "user": USER, "assistant": ASSISTANT}
NAMES = {v: k for k, v in ROLES.items()}
#: Legal next states (the automaton).
LEGAL = {START: (SYSTEM, USER), SYSTEM: (USER,), USER: (ASSISTANT,), ASSISTANT: (USER,)}
INF = 1 << 40
#: Turns that are solved one after another; the chunks of a conversation go side by side.
CHUNK = 256


@dataclass(frozen=True)
class RepairCosts:
    merge: int = 1
    relabel: int = 2
    unknown: int = 1
    insert: int = 3


class Repair:
    """Cost tables of single turns under given costs; the rest is lookup and addition."""

    def __init__(self, costs: RepairCosts = RepairCosts()):
        self.costs = costs
        # cheapest way from a state to the state just before a message of role q: (cost, roles inserted)
        self.fill: dict[tuple[int, int], tuple[int, tuple[int, ...]]] = {}
        for s in range(4):
            reach, frontier = {s: ()}, [s]
            while frontier:
                x = frontier.pop(0)
                for y in LEGAL[x]:
                    if y not in reach and y != SYSTEM:
                        reach[y] = (*reach[x], y)
                        frontier.append(y)
            for q in (SYSTEM, USER, ASSISTANT):
                ways = [p for x, p in reach.items() if q in LEGAL[x]]
                if ways:
                    best = min(ways, key=lambda p: (len(p), p))
                    self.fill[s, q] = (costs.insert * len(best), best)
        #: by role given, state before, state after
        self.turn = np.array([[[self.step(s, r, q)[0] if q else INF for q in range(4)] for s in range(4)] for r in range(4)], dtype=np.int64)
        # closing: the empty turns that a conversation lacks at its end
        self.close = np.array([0, 2 * costs.insert, costs.insert, 0], dtype=np.int64)
        self.closing = {START: (), SYSTEM: (USER, ASSISTANT), USER: (ASSISTANT,), ASSISTANT: ()}

    def step(self, s: int, r: int, q: int) -> tuple[int, str, tuple[int, ...]]:
        """Cost, action and inserted roles of giving role q to a turn of role r after state s."""
        ways = [(self.fill[s, q][0], "keep", self.fill[s, q][1])] if (s, q) in self.fill else []
        if s == q:
            ways.append((self.costs.merge, "merge", ()))
        if not ways:
            return INF, "", ()
        cost, action, inserted = min(ways, key=lambda w: w[0])
        return cost + (self.costs.unknown if not r else self.costs.relabel * (r != q)), action, inserted

    # ------------------------------------------------------------- many runs at once
    @staticmethod
    def _waves(lengths: np.ndarray):
        """Runs by falling length, and for each place the number of runs that have it."""
        order = np.argsort(-lengths, kind="stable")
        most = int(lengths.max(initial=0))
        return order, np.searchsorted(-lengths[order], -np.arange(1, most + 1), side="right")

    def products(self, codes: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Min-plus product of the turns of each run: cost by state before and after."""
        order, alive = self._waves(lengths)
        out = np.broadcast_to(np.where(np.eye(4, dtype=bool), 0, INF), (len(starts), 4, 4)).copy()
        first = starts[order]
        for k, n in enumerate(alive.tolist()):
            step = self.turn[codes[first[:n] + k]]
            out[:n] = np.minimum((out[:n, :, :, None] + step[:, None, :, :]).min(axis=2), INF)
        back = np.empty_like(out)
        back[order] = out
        return back

    def moves(self, codes: np.ndarray, starts: np.ndarray, lengths: np.ndarray, to_go: np.ndarray) -> np.ndarray:
        """State after each turn by the state before it, on the cheapest repair; smaller states first.

        ``to_go`` has for each run the cost beyond its end by the state there.
        """
        order, alive = self._waves(lengths)
        first, left = starts[order], to_go[order].copy()
        out = np.zeros((len(codes), 4), dtype=np.int8)
        for k in range(len(alive) - 1, -1, -1):
            n = int(alive[k])
            at = first[:n] + k
            cost = self.turn[codes[at]] + left[:n, None, :]
            out[at] = cost.argmin(axis=2)
            left[:n] = cost.min(axis=2)
        return out

    def follow(self, moves: np.ndarray, starts: np.ndarray, lengths: np.ndarray, entry: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """State before each turn, and the state after each run, from the entry states."""
        order, alive = self._waves(lengths)
        first, state = starts[order], entry[order].astype(np.int64)
        before = np.zeros(len(moves), dtype=np.int8)
        for k, n in enumerate(alive.tolist()):
            at = first[:n] + k
            before[at] = state[:n]
            state[:n] = moves[at, state[:n]]
        ends = np.empty_like(state)
        ends[order] = state
        return before, ends

    @staticmethod
    def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.minimum((a[:, :, None] + b[None, :, :]).min(axis=1), INF)

    def solve(self, codes: np.ndarray, starts: np.ndarray, lengths: np.ndarray, to_go: np.ndarray, entry: np.ndarray):
        """(state before each turn, state after it) of runs with any lengths; chunks go side by side."""
        pieces = np.maximum(1, -(-lengths // CHUNK))
        run = np.repeat(np.arange(len(starts)), pieces)
        number = np.arange(len(run)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        c_start = starts[run] + number * CHUNK
        c_length = np.minimum(CHUNK, lengths[run] - number * CHUNK)
        c_go, c_entry = to_go[run].copy(), entry[run].copy()
        long = np.flatnonzero(pieces > 1)
        chunks_of = {int(r): np.flatnonzero(run == r) for r in long}
        for own in chunks_of.values():
            matrix = self.products(codes, c_start[own], c_length[own])
            for k in range(len(own) - 2, -1, -1):
                c_go[own[k]] = (matrix[k + 1] + c_go[own[k + 1]][None, :]).min(axis=1)
        moves = self.moves(codes, c_start, c_length, c_go)
        for own in chunks_of.values():
            ends = [self.follow(moves, c_start[own], c_length[own], np.full(len(own), s))[1] for s in range(4)]
            for k in range(1, len(own)):
                c_entry[own[k]] = ends[int(c_entry[own[k - 1]])][k - 1]
        before, _ = self.follow(moves, c_start, c_length, c_entry)
        return before, moves[np.arange(len(codes)), before]


def role_code(role: Column) -> Column:
    """1 system, 2 user, 3 assistant, 0 for null and unknown roles; case and blanks around don't count."""
    name = F.lower(F.btrim(role, F.lit(" \t\n\r\f\x0b")))
    code = F.lit(0)
    for known, k in ROLES.items():
        code = F.when(name == known, k).otherwise(code)
    return code.cast("tinyint")


def escape_markers(text: Column) -> Column:
    r"""Text in which no role marker can begin: ``<|`` gets a backslash, ``<\|`` a second one, and so on."""
    return F.regexp_replace(text, r"<(\\*)\|", r"<\\$1|")


def unescape_markers(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\(\\*)\|", r"<$1|")


def _message(role: int, text: str) -> str:
    return f"<|{NAMES[role]}|>\n{text}"


class Rendering:
    """What stands around a turn's text, by state before, role given and role taken."""

    def __init__(self, model: Repair):
        head, inserted, action = [], [], []
        for s in range(4):
            for r in range(4):
                for q in range(4):
                    _, how, filled = model.step(s, r, q) if q else (0, "", ())
                    # every message ends where the next begins, so a merge only adds a line
                    head.append("".join(_message(x, "\n") for x in filled) + ("" if how == "merge" or not q else _message(q, "")))
                    inserted.append("+".join(NAMES[x] for x in filled) or None)
                    action.append(how if r == q else {"keep": "relabel", "merge": "relabel+merge", "": ""}[how])
        tails = [model.closing[q] for q in range(4)]
        self.head, self.inserted, self.action = (pa.array(x, pa.string()) for x in (head, inserted, action))
        self.tail = pa.array(["\n" + "".join(_message(x, "\n") for x in t) for t in tails] + ["\n"])
        self.after = pa.array(["+".join(NAMES[x] for x in t) or None for t in tails] + [None], pa.string())
        self.role = pa.array([NAMES.get(q) for q in range(4)], pa.string())


OUT = "conv_id long, turn long, role string, role_out string, action string, inserted_before string, inserted_after string, rendered string"


def _identity(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    ids = batch.column("conv_id")
    return pc.fill_null(ids, 0).to_numpy(zero_copy_only=False), pc.is_null(ids).to_numpy(zero_copy_only=False)


def _runs(batches):
    """Batches cut so that none ends inside a conversation; the rows of a partition are sorted by it."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        ids, null = _identity(batch)
        if held:
            last, last_null = _identity(held[-1].slice(held[-1].num_rows - 1))
            if (last[0], last_null[0]) != (ids[0], null[0]):
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held = []
        edge = np.flatnonzero((ids[1:] != ids[:-1]) | (null[1:] != null[:-1])) + 1
        if len(edge):
            yield pa.Table.from_batches([*held, batch.slice(0, int(edge[-1]))]).combine_chunks().to_batches()[0]
            held = []
            batch = batch.slice(int(edge[-1]))
        held.append(batch)
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _spans(batch: pa.RecordBatch):
    """Keys (None for null), starts and lengths of the conversations of a cut batch, and the role codes."""
    ids, null = _identity(batch)
    cut = np.flatnonzero(np.concatenate(([True], (ids[1:] != ids[:-1]) | (null[1:] != null[:-1]), [True])))
    keys = [None if n else int(i) for i, n in zip(ids[cut[:-1]], null[cut[:-1]], strict=True)]
    return keys, cut[:-1], np.diff(cut), batch.column("code").to_numpy(zero_copy_only=False).astype(np.int64)


def repair(conversations: DataFrame, costs: RepairCosts = RepairCosts(), partitions: int | None = None) -> DataFrame:
    """One row per given turn: its repaired role, what was done, and its piece of the rendering.

    Turns are ordered by turn (nulls first), then role, then a hash of the text.
    The pieces of a conversation in that order are its rendering; empty inserted
    turns are part of the piece of the turn that they precede, or at the end
    follow. Null texts render as empty, null or unknown roles take the cheapest
    role. Rows with a null conv_id are one conversation. Repeated rows are turns
    of their own. Other columns are not read; an empty table gives no rows.
    A text can't forge a turn: its ``<|`` is escaped as ``<\\|`` (see
    ``escape_markers``), and ``unescape_markers`` takes that back.
    """
    spark = conversations.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    order = ["conv_id", "turn", "role", "h", "p"]
    turns = conversations.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", F.coalesce("text", F.lit("")).alias("text")
    ).withColumn("h", F.xxhash64("text")).withColumn("p", F.spark_partition_id())
    # a part is what one partition holds of a conversation
    turns = turns.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())
    turns = durable(turns.select("conv_id", "turn", "role", role_code(F.col("role")).alias("code"), escape_markers(F.col("text")).alias("text"), "part"))
    model = Repair(costs)

    spans = turns.groupBy("conv_id").agg(F.min("part").alias("a"), F.max("part").alias("b")).where("a < b").select("conv_id")
    # at most one conversation crosses each border of partitions, so these are fewer than the partitions
    crossing = F.broadcast(spans.withColumnRenamed("conv_id", "c_id"))
    split = turns.join(crossing, turns["conv_id"].eqNullSafe(crossing["c_id"]), "left_semi").select("conv_id", "part", "code")

    def summaries(batches):
        for batch in _runs(batches):
            keys, starts, lengths, codes = _spans(batch)
            for key, start, length in zip(keys, starts.tolist(), lengths.tolist(), strict=True):
                cuts = np.arange(start, start + length, CHUNK)
                total = None
                for m in model.products(codes, cuts, np.minimum(CHUNK, start + length - cuts)):
                    total = m if total is None else model.times(total, m)
                yield pa.RecordBatch.from_arrays([pa.array([key], pa.int64()), batch.column("part").slice(0, 1), pa.array([total.ravel().tolist()], pa.list_(pa.int64()))], ["conv_id", "part", "m"])

    #: cost beyond a part by the state at its end, and whether the conversation ends there
    to_go: dict[tuple[int | None, int], tuple[np.ndarray, bool]] = {}
    if spans.limit(1).count():
        parts_of: dict[int | None, list] = {}
        for row in split.mapInArrow(summaries, "conv_id long, part int, m array<long>").collect():  # a row or two for each partition
            parts_of.setdefault(row.conv_id, []).append((row.part, np.array(row.m, dtype=np.int64).reshape(4, 4)))
        for conv, own in parts_of.items():
            left = model.close
            for k, (part, m) in reversed(list(enumerate(sorted(own, key=lambda x: x[0])))):
                to_go[conv, part] = (left, k == len(own) - 1)
                left = (m + left[None, :]).min(axis=1)
    shipped_go = spark.sparkContext.broadcast(to_go)

    def solved(batch, entries):
        keys, starts, lengths, codes = _spans(batch)
        part = batch.column("part")[0].as_py()
        found = [shipped_go.value.get((key, part)) for key in keys] if shipped_go.value else [None] * len(keys)
        go = np.stack([model.close if f is None else f[0] for f in found])
        closed = np.array([f is None or f[1] for f in found])
        begin = np.array([entries.get((key, part), START) for key in keys] if entries else [START] * len(keys))
        return keys, part, starts, lengths, codes, closed, model.solve(codes, starts, lengths, go, begin)

    def passages(batches):
        for batch in _runs(batches):
            ends = []
            for s in range(4):
                keys, part, starts, lengths, _, _, (_, after) = solved(batch, dict.fromkeys([(k, batch.column("part")[0].as_py()) for k in _spans(batch)[0]], s))
                ends.append(after[starts + lengths - 1].tolist())
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array([part] * len(keys), pa.int32()), pa.array([list(x) for x in zip(*ends, strict=True)], pa.list_(pa.int32()))], ["c", "part", "ends"])

    entries: dict[tuple[int | None, int], int] = {}
    if to_go:
        state: dict[int | None, int] = {}
        for row in sorted(split.mapInArrow(passages, "c long, part int, ends array<int>").collect(), key=lambda r: r.part):
            entries[row.c, row.part] = state.get(row.c, START)
            state[row.c] = row.ends[entries[row.c, row.part]]
    shipped = spark.sparkContext.broadcast(entries)
    look = Rendering(model)

    def render(batches):
        for batch in _runs(batches):
            _, _, starts, lengths, codes, closed, (before, after) = solved(batch, shipped.value)
            how = pa.array(before.astype(np.int64) * 16 + codes * 4 + after)
            end = np.full(len(codes), 4)
            last = (starts + lengths - 1)[closed]
            end[last] = after[last]
            end = pa.array(end)
            piece = pc.binary_join_element_wise(look.head.take(how), batch.column("text").cast(pa.string()), look.tail.take(end), "")
            columns = [batch.column("conv_id"), batch.column("turn"), batch.column("role"), look.role.take(pa.array(after)), look.action.take(how), look.inserted.take(how), look.after.take(end), piece]
            yield pa.RecordBatch.from_arrays([c.cast(pa.string()) if k not in (0, 1) else c for k, c in enumerate(columns)], [x.split()[0] for x in OUT.split(", ")])

    return turns.mapInArrow(render, OUT)


def op5_chat_format(spark, sf_dir: str) -> DataFrame:
    """Repair and rendering of all conversations; one row per given turn.

    Null texts, roles, turns and conv_ids, ties, repeats and empty tables are as
    in ``repair``: every given row comes back once.
    """
    return repair(spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text"))
