"""Secret scanning over a trigram inverted index, with DataFrame functions only.

From each rule's regex a Boolean query over trigrams is derived that every match
must satisfy. The index holds postings for the trigrams of all queries, cut to
blocks of bounded size; a query intersects and unites postings, and only its
candidates are verified with the regex. A rule without mandatory trigrams scans
every text. Texts are known to the index by their hash: a collision can only add
a candidate, never lose one.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import durable, small_side

#: Keys aimed at for one block of a posting list.
BLOCK_KEYS = 20_000
#: Trigrams used of one conjunction; fewer trigrams only widen the candidates.
MOST_TRIGRAMS = 3
#: Matches whose offsets are summed in one step.
CHUNK = 128


@dataclass(frozen=True)
class Rule:
    """``value_group`` of a match must have ``least`` characters, or the match is dropped."""

    kind: str
    regex: str
    value_group: int = 0
    least: int = 0


# The three base rules, then the ones that add spans.
RULES = (
    Rule("assign", r"""((?i)password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", r"[0-9a-f]+", 0, 24),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]+", 0, 40),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 0, 40),
    Rule("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----", 0, 0),
)
BASE = 3


# ---------------------------------------------------------------- Boolean queries
MOST_STRINGS = 64


def _strings(items) -> list[set[str] | None]:
    """For each element of a parsed sequence its finite set of texts, or None."""
    out = []
    for op, arg in items:
        name = str(op)
        if name == "LITERAL":
            out.append({chr(arg).lower()})
        elif name == "IN":
            chars: set[str] | None = set()
            for o, a in arg:
                if str(o) == "LITERAL":
                    chars.add(chr(a).lower())
                elif str(o) == "RANGE" and a[1] - a[0] < 8:
                    chars |= {chr(c).lower() for c in range(a[0], a[1] + 1)}
                else:
                    chars = None
                    break
            out.append(chars if chars and len(chars) <= 8 else None)
        elif name == "SUBPATTERN":
            out.extend(_strings(arg[3]))
        elif name == "BRANCH":
            whole: set[str] | None = set()
            for branch in arg[1]:
                parts = _strings(branch)
                if any(p is None for p in parts):
                    whole = None
                    break
                whole |= reduce(lambda x, y: {a + b for a in x for b in y}, parts, {""})
            out.append(whole)
        elif name in ("MAX_REPEAT", "MIN_REPEAT"):
            low, high, inner = arg
            parts = _strings(inner)
            known = None if any(p is None for p in parts) else reduce(lambda x, y: {a + b for a in x for b in y}, parts, {""})
            if (low, high) == (0, 1) and known:
                out.append(known | {""})
            else:
                out.append(None)
        else:
            out.append(None)
    return out


def trigram_query(regex: str) -> list[frozenset[str]]:
    """Disjunction of conjunctions of lower-cased trigrams that each match must contain.

    Empty if the regex has no mandatory trigram.
    """
    import re._parser as parser

    plain = regex.replace("(?i)", "")
    best: list[frozenset[str]] = []

    def close(run: set[str]):
        """A mandatory run of text: one of these strings occurs in the match."""
        nonlocal best
        clauses = {frozenset(s[k : k + 3] for k in range(len(s) - 2)) for s in run}
        if frozenset() in clauses:
            return
        clauses = [c for c in clauses if not any(d < c for d in clauses)]
        # conjunction with what is known so far, in disjunctive form
        joint = [a | b for a in best for b in clauses] if best else clauses
        best = joint if len(joint) <= MOST_STRINGS else best

    run = {""}
    for part in _strings(parser.parse(plain)):
        if part is None or len(run) * len(part) > MOST_STRINGS:
            close(run)
            run = {""} if part is None else part
        else:
            run = {a + b for a in run for b in part}
    close(run)
    return sorted(best, key=sorted)


def _lean(clause: frozenset[str]) -> tuple[str, ...]:
    own = sorted(clause)
    return tuple(own[round(k * (len(own) - 1) / (MOST_TRIGRAMS - 1))] for k in range(MOST_TRIGRAMS)) if len(own) > MOST_TRIGRAMS else tuple(own)


# -------------------------------------------------------------------------- index
def trigram_index(texts: DataFrame, trigrams: list[str]) -> DataFrame:
    """(block, postings map trigram -> sorted keys) over all texts, columns ``key`` and ``t``."""
    found = lambda low: F.array_compact(F.array(*(F.when(F.contains(low, F.lit(g)), F.lit(g)) for g in trigrams)))
    # bound as a variable, the lower-cased text is made once and not once for each trigram
    present = F.element_at(F.transform(F.array(F.lower("t")), found), 1)
    blocks = max(32, math.ceil(texts.count() / BLOCK_KEYS))
    rows = texts.select("key", F.explode(present).alias("trigram")).withColumn("block", F.pmod("key", F.lit(blocks)))
    lists = rows.groupBy("block", "trigram").agg(F.sort_array(F.collect_set("key")).alias("keys"))
    return lists.groupBy("block").agg(F.map_from_entries(F.collect_list(F.struct("trigram", "keys"))).alias("postings"))


def candidates(index: DataFrame, queries: dict[str, list[tuple[str, ...]]]) -> DataFrame:
    """(key, kinds) of the texts that satisfy the queries, from the postings alone."""
    none = F.array().cast("array<long>")
    posting = lambda g: F.coalesce(F.col("postings").getItem(g), none)

    def solve(clauses):
        sets = [reduce(F.array_intersect, (posting(g) for g in clause)) for clause in clauses]
        return reduce(F.array_union, sets)

    found = F.array(*(F.struct(F.lit(kind).alias("kind"), solve(clauses).alias("keys")) for kind, clauses in queries.items()))
    rows = index.select(F.explode(found).alias("f")).select("f.kind", F.explode("f.keys").alias("key"))
    return rows.groupBy("key").agg(F.collect_set("kind").alias("kinds"))


# ----------------------------------------------------------------------- verifying
def match_sizes(t: Column, rule: Rule) -> Column:
    """Array of struct(gap, n, v): code points before a match, in it and in its value.

    The pieces between matches and the matches alternate, so these sum up to offsets.
    """
    whole = F.regexp_extract_all(t, F.lit(rule.regex), F.lit(0))
    value = F.regexp_extract_all(t, F.lit(rule.regex), F.lit(rule.value_group))
    pieces = F.split(t, rule.regex, -1)
    return F.transform(
        F.arrays_zip(F.slice(pieces, 1, F.size(whole)).alias("p"), whole.alias("m"), value.alias("v")),
        lambda x: F.struct(F.length(x["p"]).alias("gap"), F.length(x["m"]).alias("n"), F.length(x["v"]).alias("v")),
    )


def match_spans(sizes: Column, order: int, rule: Rule) -> Column:
    """Array of struct(start, rank, end, kind) of the matches that are long enough; sums go chunk by chunk."""
    chunks = F.transform(F.sequence(F.lit(0), F.floor((F.size(sizes) - 1) / CHUNK).cast("int")), lambda k: F.slice(sizes, k * CHUNK + 1, CHUNK))
    length = lambda c: F.aggregate(c, F.lit(0), lambda a, x: a + x["gap"] + x["n"])
    starts = F.aggregate(chunks, F.array(F.lit(0)), lambda a, c: F.array_append(a, F.element_at(a, -1) + length(c)))
    empty = F.array().cast("array<struct<start:int,rank:int,end:int,kind:string>>")

    def walk(chunk, k):
        def step(acc, x):
            begin = acc["at"] + x["gap"]
            end = begin + x["n"]
            one = F.struct(begin.alias("start"), F.lit(order).alias("rank"), end.alias("end"), F.lit(rule.kind).alias("kind"))
            return F.struct(end.alias("at"), F.when(x["v"] >= rule.least, F.array_append(acc["out"], one)).otherwise(acc["out"]).alias("out"))

        return F.aggregate(chunk, F.struct(F.element_at(starts, k + 1).alias("at"), empty.alias("out")), step, lambda acc: acc["out"])

    return F.when(F.size(sizes) > 0, F.flatten(F.transform(chunks, walk))).otherwise(empty)


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(id, one array of spans for each rule) for every row, in whole texts.

    Null text counts as empty. Rows with equal texts share a posting.
    """
    value = F.coalesce(F.col(text), F.lit(""))
    texts = docs.select(F.col(key).alias("id"), value.alias("t"), F.xxhash64(value).alias("key"))
    queries = {r.kind: [_lean(c) for c in q] for r in rules if (q := trigram_query(r.regex))}
    wanted = sorted({g for q in queries.values() for c in q for g in c})
    found = durable(candidates(trigram_index(texts.select("key", "t"), wanted), queries))
    marked = texts.join(small_side(found), "key", "left")
    sized = marked
    for rule in rules:
        # a run of one class is maximal, so a first look for a long one spares most texts
        long_run = re.fullmatch(r"(\[[^\]]+\])\+", rule.regex)
        if rule.kind in queries:
            look = F.coalesce(F.array_contains("kinds", rule.kind), F.lit(False))
        elif long_run:
            look = F.col("t").rlike(f"{long_run[1]}{{{rule.least}}}")
        else:
            look = F.lit(True)
        sizes = match_sizes(F.col("t"), rule)
        sized = sized.withColumn(f"size_{rule.kind}", F.when(look, sizes).otherwise(F.array().cast("array<struct<gap:int,n:int,v:int>>")))
    sized = sized.select("id", *(f"size_{r.kind}" for r in rules))
    return sized.select("id", *(match_spans(F.col(f"size_{r.kind}"), k, r).alias(r.kind) for k, r in enumerate(rules)))


def _joined(kinds: list[str]) -> Column:
    spans = F.array_sort(F.concat(*(F.col(k) for k in kinds)))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def op10_secrets(spark, sf_dir: str) -> DataFrame:
    """Secrets in every document: counts by base kind, digest of the base spans, all spans.

    Null and empty texts have none; repeated rows and null ids each come back, and
    an empty table gives no rows. Whole texts are searched, however long.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = scan(docs)
    base = [r.kind for r in RULES[:BASE]]
    return found.select(
        F.col("id").alias("doc_id"),
        *(F.size(k).cast("long").alias(f"n_{k}") for k in base),
        F.sha2(_joined(base), 256).alias("base_sha256"),
        _joined([r.kind for r in RULES]).alias("spans"),
    )


def _sql_spans(rule: Rule, rank: int) -> str:
    regex = rule.regex.replace("((?i)password", "((?i:password").replace("api_?key)", "api_?key))").replace("'", "''")
    return f"""
  SELECT doc_id, {rank} AS rank, '{rule.kind}' AS kind, b AS start, b + n AS stop FROM (
    SELECT doc_id, list_sum(gaps[:k]) + coalesce(list_sum(sizes[:k - 1]), 0) AS b, sizes[k] AS n, vals[k] AS v FROM (
      SELECT *, unnest(range(1, len(sizes) + 1)) AS k FROM (
        SELECT doc_id, list_transform(regexp_extract_all(t, '{regex}'), lambda x: length(x)) AS sizes,
               list_transform(regexp_extract_all(t, '{regex}', {rule.value_group}), lambda x: length(x)) AS vals,
               list_transform(string_split_regex(t, '{regex}'), lambda x: length(x)) AS gaps FROM d)))
  WHERE v >= {rule.least}"""


SQL_OP10 = (
    "WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),\ns AS ("
    + "\n  UNION ALL".join(_sql_spans(r, k) for k, r in enumerate(RULES))
    + """),
g AS (
  SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
         string_agg(kind || ':' || start || ':' || stop, ',' ORDER BY start, rank) FILTER (rank < 3) AS base,
         string_agg(kind || ':' || start || ':' || stop, ',' ORDER BY start, rank) AS spans
  FROM s GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN g ON d.doc_id = g.doc_id
"""
)
