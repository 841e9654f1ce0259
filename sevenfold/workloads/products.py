"""Products: the fold matrices by every method, and those of the other tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from sevenfold.operators import grids, scaling
from sevenfold.operators import relational as rel
from sevenfold.operators.hybrid import budgeted, chain_multiply, greedy, hybrid, peel, peel_levels, power, sql_multiply, wide
from sevenfold.operators.leaf import LeafSpec
from sevenfold.operators.multiply import multiply, multiply_cells
from sevenfold.operators.relational import checked_broadcast
from sevenfold.operators.tiles import cells_to_tiles, durable, exact_twin, relayout, tiles_to_cells
from sevenfold.operators.tiles import transpose as transpose_tiles
from sevenfold.plans.layout import LayoutSpec
from sevenfold.sources.matrices import EMBED_SQL, FOLD_SQL, TRADE_SQL, cells_from, embedding_cells, fold_pair, table, trade
from sevenfold.workloads.registry import FOLD_PRODUCT, as_cells, fold_tiles, query


# ------------------------------------------------------- the product by every method
MULTIPLIERS = {
    "w_hybrid_wide": lambda a, b: wide(a, b, 49),
    "w_hybrid_stepwise": lambda a, b: wide(a, b, 49, exchange="stepwise"),
    "w_hybrid_fused": lambda a, b: wide(a, b, 49, fuse=2),
    "w_hybrid_budgeted": lambda a, b: budgeted(a, b, 7, 9 * a.n_rows**2 / 7),
    "w_hybrid_greedy": lambda a, b: greedy(a, b, 7, 3 * a.n_rows**2 / 4),
    "w_hybrid_interleaved": lambda a, b: hybrid(a, b, "WS"),
    "w_hybrid_c2": lambda a, b: hybrid(a, b, "W", c=2),
    "w_hybrid_c3": lambda a, b: hybrid(a, b, "W", c=3),
    "w_hybrid_c6": lambda a, b: hybrid(a, b, "W", c=6),
    "w_hybrid_s7a18": lambda a, b: hybrid(a, b, "WW", scheme="s7a18"),
    "w_hybrid_c8": lambda a, b: hybrid(a, b, "WW", scheme="c8"),
    "w_hybrid_tensor4": lambda a, b: hybrid(a, b, "W", scheme="tensor4"),
    "w_hybrid_decimal": lambda a, b: hybrid(exact_twin(a), exact_twin(b), "W"),
    "w_peel_levels": lambda a, b: peel_levels(a, b, 2),
    "w_leaf_fast": lambda a, b: hybrid(a, b, "W", leaf=LeafSpec(levels=2, cutoff=8)),
    "w_leaf_tiles": lambda a, b: hybrid(a, b, "W", leaf=LeafSpec(kind="tiles")),
    "w_multiply": lambda a, b: multiply(a, b)[0],
    "w_grid2d": lambda a, b: grids.grid2d(a, b, 4),
    "w_grid2d_panels": lambda a, b: grids.grid2d(a, b, 2, panel=4),
    "w_grid2d_shift": lambda a, b: grids.grid2d_shift(a, b, 4),
    "w_grid2d_rounds": lambda a, b: grids.grid2d_shift(a, b, 2, rounds=True),
    "w_grid3d": lambda a, b: grids.grid3d(a, b, 2),
    "w_grid25d": lambda a, b: grids.grid25d(a, b, 32, 2),
    "w_grid25d_memory": lambda a, b: grids.grid25d(a, b, 64, memory=3 * a.n_rows**2 * 2 / 64),
    "w_grid2d_fast": lambda a, b: grids.grid2d_fast(a, b, 2),
    "w_grid2d_fast_levels0": lambda a, b: grids.grid2d_fast(a, b, 2, 0),
    "w_grid2d_fast_levels3": lambda a, b: grids.grid2d_fast(a, b, 2, 3),
    "w_fast_grid2d": lambda a, b: grids.fast_grid2d(a, b, 1, 2),
    "w_fast_grid2d_packed": lambda a, b: grids.fast_grid2d(a, b, 1, 2, pack=True),
    "w_grid25d_fast": lambda a, b: grids.grid25d_fast(a, b, 32, 2),
    "w_grid25d_fast_levels3": lambda a, b: grids.grid25d_fast(a, b, 8, 2, 3),
    "w_fast_grid25d": lambda a, b: grids.fast_grid25d(a, b, 8, 2, levels=1),
    "w_fast_grid25d_opt": lambda a, b: grids.fast_grid25d(a, b, 8, 2, "opt", memory=a.n_rows**2 / 10),
}


def _product_query(multiply_tiles):
    return lambda spark, d: as_cells(tiles_to_cells(multiply_tiles(*fold_tiles(spark, d))))


for _name, _multiply in MULTIPLIERS.items():
    query(_name, FOLD_PRODUCT)(_product_query(_multiply))


@query("w_relayout", f"WITH {FOLD_SQL} SELECT * FROM a")
def w_relayout(spark, d):
    """The first factor dealt to 49 logical workers by the layout of one recursion level."""
    a, _, n = fold_pair(spark, d)
    spec = LayoutSpec(n // 56 * 98, 49, 1)
    return as_cells(tiles_to_cells(relayout(cells_to_tiles(a, n, n, spec.block[0]), spec, 8)))


@query("w_lib_block", FOLD_PRODUCT)
def w_lib_block(spark, d):
    return grids.lib_block(*fold_tiles(spark, d))


@query("w_sql", FOLD_PRODUCT)
def w_sql(spark, d):
    a, b, _ = fold_pair(spark, d)
    return as_cells(sql_multiply(a, b))


for _hint in ("shuffle_hash", "merge"):
    query(f"o_join_{'hash' if _hint == 'shuffle_hash' else 'merge'}", FOLD_PRODUCT)(lambda spark, d, h=_hint: as_cells(sql_multiply(*fold_pair(spark, d)[:2], hint=h)))

# -------------------------------------------------------------------- other products
_SQUARE = "SELECT x.i AS i, y.j AS j, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM {m} x JOIN {m} y ON x.j = y.i GROUP BY 1, 2 HAVING sum(x.v * y.v) <> 0"
TRADE_SQUARE = f"WITH {TRADE_SQL} {_SQUARE.format(m='t')}"


@query("w_pad_trade", TRADE_SQUARE)
def w_pad_trade(spark, d):
    t = cells_to_tiles(trade(spark, d), 25, 25, 4)
    t = t.with_df(durable(t.df))
    return as_cells(tiles_to_cells(hybrid(t, t, "W")))


@query("w_peel_trade", TRADE_SQUARE)
def w_peel_trade(spark, d):
    t = durable(trade(spark, d))
    return as_cells(peel(t, t, (25, 25, 25), tile=4, schedule="W"))


_RECT = """WITH x AS (SELECT CAST(c_nationkey AS BIGINT) AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2),
y AS (SELECT l_partkey AS i, l_suppkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2)
SELECT x.i AS i, y.j AS j, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM x JOIN y ON x.j = y.i GROUP BY 1, 2"""


@query("w_rect_cust_supp", _RECT)
def w_rect_cust_supp(spark, d):
    li = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    o, c = table(spark, d, "orders", "o_orderkey", "o_custkey"), table(spark, d, "customer", "c_custkey", "c_nationkey")
    x = cells_from(li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")), F.col("c_nationkey"), F.col("l_partkey"), F.col("l_quantity"))
    y = cells_from(li, F.col("l_partkey"), F.col("l_suppkey"), F.col("l_quantity"))
    parts, supp = (table(spark, d, t, k).agg(F.max(k)).first()[0] + 1 for t, k in (("part", "p_partkey"), ("supplier", "s_suppkey")))
    return as_cells(multiply_cells(x, y, (25, parts, supp), 16))


@query("w_gram_embed", f"WITH {EMBED_SQL} SELECT x.i AS i, y.i AS j, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM m x JOIN m y ON x.j = y.j WHERE x.i % 50 = 0 GROUP BY 1, 2 HAVING sum(x.v * y.v) <> 0")
def w_gram_embed(spark, d):
    """Every vector whose id is divisible by 50 against all vectors; leaves are joins over tiles, so no task holds one whole."""
    cells = durable(embedding_cells(spark, d))
    rows, cols = (v + 1 for v in cells.agg(F.coalesce(F.max("i"), F.lit(0)), F.coalesce(F.max("j"), F.lit(0))).first())
    asked = cells.where("i % 50 = 0").withColumn("i", F.expr("i div 50"))
    e = cells_to_tiles(cells, rows, cols, 32)
    out = tiles_to_cells(hybrid(cells_to_tiles(asked, (rows - 1) // 50 + 1, cols, 32), transpose_tiles(e), "W", leaf=LeafSpec(kind="tiles")))
    return as_cells(out.withColumn("i", F.col("i") * 50))


@query("w_cov_embed", f"WITH {EMBED_SQL} SELECT label, x.j AS i, y.j AS j, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM m x JOIN m y ON x.i = y.i JOIN embeddings ON vec_id = x.i GROUP BY 1, 2, 3 HAVING sum(x.v * y.v) <> 0")
def w_cov_embed(spark, d):
    e = embedding_cells(spark, d).join(table(spark, d, "embeddings", F.col("vec_id").alias("i"), "label"), "i")
    y = e.select("i", F.col("j").alias("k"), F.col("v").alias("w"))
    return e.join(y, "i").groupBy("label", F.col("j").alias("i"), F.col("k").alias("j")).agg(F.sum(F.col("v") * F.col("w")).alias("v")).where("v <> 0")


@query("w_cosupply", "WITH y AS (SELECT l_partkey AS i, l_suppkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2) SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM y a JOIN y b ON a.i = b.i GROUP BY 1, 2")
def w_cosupply(spark, d):
    y = durable(cells_from(table(spark, d, "lineitem", "l_partkey", "l_suppkey", "l_quantity"), F.col("l_partkey"), F.col("l_suppkey"), F.col("l_quantity")))
    return as_cells(sql_multiply(rel.transpose(y), y))


@query("w_basket", "WITH x AS (SELECT DISTINCT l_orderkey AS o, p_brand AS b FROM lineitem JOIN part ON l_partkey = p_partkey) SELECT x.b AS brand, y.b AS other, count(*) AS v FROM x JOIN x y ON x.o = y.o GROUP BY 1, 2")
def w_basket(spark, d):
    li, p = table(spark, d, "lineitem", "l_orderkey", "l_partkey"), table(spark, d, "part", "p_partkey", "p_brand")
    x = li.join(p, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", F.col("p_brand").alias("brand")).distinct()
    return x.join(x.withColumnRenamed("brand", "other"), "l_orderkey").groupBy("brand", "other").agg(F.count("*").alias("v"))


@query("w_segment_priority", "SELECT c_mktsegment AS segment, o_orderpriority AS priority, count(*) AS v FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1, 2")
def w_segment_priority(spark, d):
    c, o = table(spark, d, "customer", "c_custkey", "c_mktsegment"), table(spark, d, "orders", "o_custkey", "o_orderpriority")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey")).groupBy(F.col("c_mktsegment").alias("segment"), F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("v"))


@query("w_user_type", "WITH x AS (SELECT user_id AS u, event_type AS t, count(*) AS v FROM events GROUP BY 1, 2) SELECT x.t AS kind, y.t AS other, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM x JOIN x y ON x.u = y.u GROUP BY 1, 2")
def w_user_type(spark, d):
    x = table(spark, d, "events", "user_id", "event_type").groupBy("user_id", F.col("event_type").alias("kind")).agg(F.count("*").alias("c"))
    y = x.select("user_id", F.col("kind").alias("other"), F.col("c").alias("e"))
    return x.join(y, "user_id").groupBy("kind", "other").agg(F.sum(F.col("c") * F.col("e")).alias("v"))


_TRANS = """k AS (SELECT event_type AS kind, row_number() OVER (ORDER BY event_type) - 1 AS idx FROM (SELECT DISTINCT event_type FROM events)),
p AS (SELECT lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS a, event_type AS b FROM events),
t AS (SELECT x.idx AS i, y.idx AS j, count(*) AS v FROM p JOIN k x ON a = x.kind JOIN k y ON b = y.kind GROUP BY 1, 2)"""


def _transition(spark, d):
    e = table(spark, d, "events", "user_id", "ts", "event_id", "event_type")
    keys = durable(rel.index_keys(e, "event_type"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    pairs = e.select(F.lag("event_type").over(w).alias("a"), F.col("event_type").alias("b"))
    x, y = keys.select(F.col("key").alias("a"), F.col("idx").alias("x")), keys.select(F.col("key").alias("b"), F.col("idx").alias("y"))
    return cells_from(pairs.join(F.broadcast(x), "a").join(F.broadcast(y), "b"), F.col("x"), F.col("y"), F.lit(1))


@query("w_transition", f"WITH {_TRANS} SELECT * FROM t")
def w_transition(spark, d):
    return as_cells(_transition(spark, d))


@query("w_transition_pow4", f"WITH {_TRANS}, s AS ({_SQUARE.format(m='t')}) {_SQUARE.format(m='s')}")
def w_transition_pow4(spark, d):
    """Integers of 64 bits as in the SQL, where all fit; on larger tables decimals, and there the SQL raises."""
    return power(_transition(spark, d), 4).select("i", "j", "v")


_ROLE = """k AS (SELECT role, row_number() OVER (ORDER BY role) - 1 AS idx FROM (SELECT DISTINCT role FROM conversations)),
p AS (SELECT lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS a, role AS b FROM conversations),
t AS (SELECT x.idx AS i, y.idx AS j, count(*) AS v FROM p JOIN k x ON a = x.role JOIN k y ON b = y.role GROUP BY 1, 2)"""


@query("w_role_transition", f"WITH {_ROLE} {_SQUARE.format(m='t')}")
def w_role_transition(spark, d):
    c = table(spark, d, "conversations", "conv_id", "turn", "role")
    keys = durable(rel.index_keys(c, "role"))
    pairs = c.select(F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("a"), F.col("role").alias("b"))
    x, y = keys.select(F.col("key").alias("a"), F.col("idx").alias("x")), keys.select(F.col("key").alias("b"), F.col("idx").alias("y"))
    t = durable(cells_from(pairs.join(F.broadcast(x), "a").join(F.broadcast(y), "b"), F.col("x"), F.col("y"), F.lit(1)))
    return as_cells(sql_multiply(t, t))


_BUCKET = "SELECT doc_id, lang, least(length(w), 31) AS b, count(*) AS v FROM (SELECT doc_id, lang, unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY 1, 2, 3"


def _doc_buckets(spark, d):
    words = table(spark, d, "documents", "doc_id", "lang", "text").select("doc_id", "lang", F.explode(F.split("text", " ", -1)).alias("w"))
    return words.groupBy("doc_id", "lang", F.least(F.length("w"), F.lit(31)).cast("long").alias("b")).agg(F.count("*").alias("v"))


@query("w_doc_term", f"WITH x AS (SELECT lang, b, sum(v) AS v FROM ({_BUCKET}) GROUP BY 1, 2) SELECT x.lang AS lang, y.lang AS other, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM x JOIN x y ON x.b = y.b GROUP BY 1, 2")
def w_doc_term(spark, d):
    x = _doc_buckets(spark, d).groupBy("lang", "b").agg(F.sum("v").alias("c"))
    y = x.select(F.col("lang").alias("other"), "b", F.col("c").alias("e"))
    return x.join(y, "b").groupBy("lang", "other").agg(F.sum(F.col("c") * F.col("e")).alias("v"))


@query("w_class_term", f"SELECT quality, toxic, CAST(b AS BIGINT) AS b, CAST(sum(v) AS BIGINT) AS v FROM labels JOIN ({_BUCKET}) x ON labels.doc_id = x.doc_id GROUP BY 1, 2, 3")
def w_class_term(spark, d):
    return table(spark, d, "labels").join(_doc_buckets(spark, d), "doc_id").groupBy("quality", "toxic", "b").agg(F.sum("v").alias("v"))


@query("w_bench_overlap", "WITH x AS (SELECT DISTINCT doc_id, unnest(string_split(text, ' ')) AS w FROM documents), y AS (SELECT DISTINCT item_id, unnest(string_split(text, ' ')) AS w FROM benchmark) SELECT doc_id AS i, item_id AS j, count(*) AS v FROM x JOIN y ON x.w = y.w GROUP BY 1, 2")
def w_bench_overlap(spark, d):
    x = table(spark, d, "documents", "doc_id", "text").select(F.col("doc_id").alias("i"), F.explode(F.array_distinct(F.split("text", " ", -1))).alias("w"))
    y = table(spark, d, "benchmark", "item_id", "text").select(F.col("item_id").alias("j"), F.explode(F.array_distinct(F.split("text", " ", -1))).alias("w"))
    # the benchmark's words go out if they are few, so no document word is hot in a shuffle
    return x.join(checked_broadcast(durable(y)), "w").groupBy("i", "j").agg(F.count("*").alias("v"))


_HOST = "regexp_extract(url, '^https?://([^/]+)', 1)"


@query("w_page_links", f"WITH x AS (SELECT {_HOST} AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS path FROM pages), y AS (SELECT host, path, count(*) AS v FROM x GROUP BY 1, 2) SELECT a.host AS host, b.host AS other, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM y a JOIN y b ON a.path = b.path GROUP BY 1, 2")
def w_page_links(spark, d):
    p = table(spark, d, "pages", "url", "html")
    x = p.select(F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("path"))
    y = x.groupBy("host", "path").agg(F.count("*").alias("c"))
    z = y.select(F.col("host").alias("other"), "path", F.col("c").alias("e"))
    return y.join(z, "path").groupBy("host", "other").agg(F.sum(F.col("c") * F.col("e")).alias("v"))


@query("w_region_rollup", f"WITH {TRADE_SQL} SELECT CAST(x.n_regionkey AS BIGINT) AS i, CAST(y.n_regionkey AS BIGINT) AS j, CAST(sum(v) AS BIGINT) AS v FROM t JOIN nation x ON t.i = x.n_nationkey JOIN nation y ON t.j = y.n_nationkey GROUP BY 1, 2")
def w_region_rollup(spark, d):
    m = cells_from(table(spark, d, "nation"), F.col("n_nationkey"), F.col("n_regionkey"), F.lit(1))
    return as_cells(chain_multiply([rel.transpose(m), trade(spark, d), m], [5, 25, 25, 5]))


@query("w_scaling")
def w_scaling(spark, d):
    """Strong scaling: one product over logical workers, every point tuned, with rates, words, shuffle bytes and speedups."""
    return scaling.strong_scaling(spark, *fold_tiles(spark, d))
