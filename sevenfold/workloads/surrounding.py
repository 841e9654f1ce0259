"""Operators around the product, one query each."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from sevenfold.functions.udfs import frobenius_udaf, register
from sevenfold.operators import relational as rel
from sevenfold.operators.leaf import tile_gemm
from sevenfold.operators.relational import checked_broadcast
from sevenfold.operators.tiles import cells_to_tiles, read_tiles, shared_folder, slice_tiles, tiles_to_cells, write_tiles
from sevenfold.sources.matrices import EMBED_SQL, FOLD_SQL, TRADE_SQL, cells_from, embedding_cells, fold_pair, table, trade
from sevenfold.workloads.products import _HOST
from sevenfold.workloads.registry import TILES, as_cells, fold_tiles, query

_A = f"WITH {FOLD_SQL} "

query("o_explode", f"WITH {EMBED_SQL} SELECT * FROM m")(embedding_cells)


@query("o_scan", "SELECT l_orderkey, l_quantity FROM lineitem")
def o_scan(s, d):
    return table(s, d, "lineitem", "l_orderkey", "l_quantity")


@query("o_fold", _A + "SELECT * FROM a")
def o_fold(s, d):
    return fold_pair(s, d)[0]


@query("o_tiles", _A + "SELECT * FROM a")
def o_tiles(s, d):
    return as_cells(tiles_to_cells(fold_tiles(s, d)[0]))


@query("o_cells", """SELECT CAST(c_nationkey AS BIGINT) AS i, CAST(year(o_orderdate) AS BIGINT) AS j, count(*) AS v
FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2""")
def o_cells(s, d):
    orders, customers = table(s, d, "orders", "o_custkey", "o_orderdate"), table(s, d, "customer", "c_custkey", "c_nationkey")
    joined = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return cells_from(joined, F.col("c_nationkey"), F.year("o_orderdate"), F.lit(1))


@query("o_slice", f"WITH {EMBED_SQL} SELECT * FROM m WHERE i >= 10 AND i < 60 AND j >= 8 AND j < 24")
def o_slice(s, d):
    return rel.slice_cells(embedding_cells(s, d), (10, 60), (8, 24))


@query("o_band", _A + "SELECT * FROM a WHERE j - i BETWEEN -2 AND 3")
def o_band(s, d):
    return rel.band(fold_pair(s, d)[0], -2, 3)


@query("o_diag", _A + "SELECT * FROM a WHERE i = j")
def o_diag(s, d):
    return rel.band(fold_pair(s, d)[0], 0, 0)


@query("o_sparsify", f"WITH {EMBED_SQL} SELECT * FROM m WHERE abs(v) > 250")
def o_sparsify(s, d):
    return rel.sparsify(embedding_cells(s, d), 250)


@query("o_transpose", f"WITH {EMBED_SQL} SELECT j AS i, i AS j, v FROM m")
def o_transpose(s, d):
    return rel.transpose(embedding_cells(s, d))


@query("o_axpy", _A + """SELECT i, j, CAST(sum(v) AS BIGINT) AS v FROM (SELECT i, j, 2 * v AS v FROM a UNION ALL SELECT i, j, -3 * v FROM b)
GROUP BY 1, 2 HAVING sum(v) <> 0""")
def o_axpy(s, d):
    return rel.axpy(2, fold_pair(s, d)[0], -3, fold_pair(s, d)[1])


@query("o_hadamard", _A + "SELECT a.i, a.j, a.v * b.v AS v FROM a JOIN b ON a.i = b.i AND a.j = b.j")
def o_hadamard(s, d):
    return rel.hadamard(*fold_pair(s, d)[:2])


@query("o_matvec", _A + """SELECT a.i, CAST(sum(a.v * x.x) AS BIGINT) AS v FROM a JOIN (SELECT j, sum(v) AS x FROM b GROUP BY j) x ON a.j = x.j
GROUP BY 1""")
def o_matvec(s, d):
    return rel.matvec(fold_pair(s, d)[0], fold_pair(s, d)[1].groupBy("j").agg(F.sum("v").alias("x")))


@query("o_outer", """SELECT CAST(x.n_nationkey AS BIGINT) AS i, CAST(y.r_regionkey AS BIGINT) AS j,
CAST(x.n_nationkey * y.r_regionkey AS BIGINT) AS v FROM nation x, region y""")
def o_outer(s, d):
    """Column times row: the one operator whose result is all pairs; the shorter vector goes out if it is counted to be small."""
    row = checked_broadcast(table(s, d, "region", "r_regionkey"))
    i, j = F.col("n_nationkey").cast("long"), F.col("r_regionkey").cast("long")
    return table(s, d, "nation", "n_nationkey").crossJoin(row).select(i.alias("i"), j.alias("j"), (i * j).alias("v"))


@query("o_scale", f"WITH {EMBED_SQL} SELECT i, j, v * (1 + label) AS v FROM m JOIN embeddings ON vec_id = i")
def o_scale(s, d):
    return (
        embedding_cells(s, d)
        .join(table(s, d, "embeddings", F.col("vec_id").alias("i"), "label"), "i")
        .select("i", "j", (F.col("v") * (1 + F.col("label"))).alias("v"))
    )


@query("o_theta", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey < r_regionkey")
def o_theta(s, d):
    regions = checked_broadcast(table(s, d, "region"))
    return table(s, d, "nation").join(regions, F.col("n_regionkey") < F.col("r_regionkey")).select("n_name", "r_name")


@query("o_range", """SELECT x.p_partkey AS p_partkey, y.p_partkey AS other FROM part x
JOIN part y ON abs(x.p_retailprice - y.p_retailprice) <= 0.25 AND x.p_partkey < y.p_partkey""")
def o_range(s, d):
    p = table(s, d, "part", "p_partkey", "p_retailprice")
    near = rel.band_join(p, p, "p_retailprice", 0.25).where("p_partkey < p_partkey_r")
    return near.select("p_partkey", F.col("p_partkey_r").alias("other"))


@query("o_asof", """SELECT DISTINCT p.user_id, p.ts, (SELECT max(v) FROM (SELECT arg_max(e.value, (e.ts, e.value)) AS v FROM events e
WHERE e.user_id = p.user_id AND e.event_type <> 'click' AND e.ts <= p.ts)) AS last_seen FROM events p WHERE event_type
= 'click'""")
def o_asof(s, d):
    e = table(s, d, "events")
    return rel.asof_last(e.where("event_type <> 'click'"), e.where("event_type = 'click'"), "user_id", "ts", "value").distinct()


@query("o_interval", """SELECT x.event_id AS event_id, y.event_id AS other FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts >
x.ts AND y.ts <= x.ts + INTERVAL 30 MINUTE""")
def o_interval(s, d):
    """Pairs of a user's events within half an hour: equality on the hour or the next, then the exact test."""
    e = table(s, d, "events", "event_id", "user_id", "ts")
    hour = F.hour("ts") + 24 * F.dayofyear("ts")
    later = e.select("user_id", hour.alias("h"), F.col("ts").alias("t2"), F.col("event_id").alias("other"))
    both = e.withColumn("h", F.explode(F.array(hour, hour + 1))).join(later, ["user_id", "h"])
    return both.where((F.col("t2") > F.col("ts")) & (F.col("t2") <= F.col("ts") + F.expr("INTERVAL 30 MINUTES"))).select("event_id", "other")


@query("o_full_diff", _A + """SELECT i, j, v FROM (SELECT coalesce(a.i, b.i) AS i, coalesce(a.j, b.j) AS j, coalesce(a.v, 0) - coalesce(b.v, 0) AS v
FROM a FULL JOIN b ON a.i = b.i AND a.j = b.j) WHERE v <> 0""")
def o_full_diff(s, d):
    return rel.diff(*fold_pair(s, d)[:2])


@query("o_left", """SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1""")
def o_left(s, d):
    return (
        table(s, d, "customer", "c_custkey")
        .join(table(s, d, "orders", "o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left")
        .groupBy("c_custkey")
        .agg(F.count("o_orderkey").alias("n"))
    )


@query("o_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 49)")
def o_semi(s, d):
    lines = table(s, d, "lineitem", "l_orderkey", "l_quantity").where("l_quantity > 49")
    return table(s, d, "orders", "o_orderkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")


@query("o_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 25)")
def o_anti(s, d):
    lines = table(s, d, "lineitem", "l_orderkey", "l_quantity").where("l_quantity > 25")
    return table(s, d, "orders", "o_orderkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("o_trace", _A + "SELECT CAST(sum(v) AS BIGINT) AS v FROM a WHERE i = j")
def o_trace(s, d):
    return rel.band(fold_pair(s, d)[0], 0, 0).agg(F.sum("v").alias("v"))


@query("o_row_sums", _A + "SELECT i, CAST(sum(v) AS BIGINT) AS v, count(*) AS n FROM a GROUP BY 1")
def o_row_sums(s, d):
    return fold_pair(s, d)[0].groupBy("i").agg(F.sum("v").alias("v"), F.count("*").alias("n"))


@query("o_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
def o_distinct(s, d):
    return (
        table(s, d, "lineitem", "l_suppkey", "l_partkey")
        .groupBy("l_suppkey")
        .agg(F.count_distinct("l_partkey").alias("n"))
    )


@query("o_grouping_sets", """SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY GROUPING SETS
((l_returnflag), (l_linestatus), ())""")
def o_grouping_sets(s, d):
    return (
        table(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity")
        .groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")], []], "l_returnflag", "l_linestatus")
        .agg(F.sum("l_quantity").cast("long").alias("v"))
    )


_TYPES = ["click", "error", "purchase", "signup", "view"]


@query("o_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in _TYPES) + " FROM events GROUP BY 1")
def o_pivot(s, d):
    """All five event types as columns, by the pivot operator."""
    counts = table(s, d, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", _TYPES).agg(F.count(F.lit(1)))
    return counts.select("user_id", *(F.coalesce(t, F.lit(0)).alias(t) for t in _TYPES))


@query("o_unpivot", """SELECT s_suppkey, 'nation' AS what, CAST(s_nationkey AS DOUBLE) AS v FROM supplier UNION ALL SELECT s_suppkey,
'balance', s_acctbal FROM supplier""")
def o_unpivot(s, d):
    return (
        table(s, d, "supplier")
        .select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
        .unpivot("s_suppkey", ["nation", "balance"], "what", "v")
    )


@query("o_sort_agg", "SELECT p_brand, min(p_name) AS low, max(p_type) AS high FROM part GROUP BY 1")
def o_sort_agg(s, d):
    return (
        table(s, d, "part")
        .groupBy("p_brand")
        .agg(F.min("p_name").alias("low"), F.max("p_type").alias("high"))
    )


@query("o_topk_row", _A + """SELECT i, j, v, r FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS r FROM a) WHERE r <= 3""")
def o_topk_row(s, d):
    return rel.topk_per_row(fold_pair(s, d)[0], 3).withColumn("r", F.col("r").cast("long"))


@query("o_rank_forms", _A + """SELECT i, j, rank() OVER w AS a1, dense_rank() OVER w AS a2, ntile(4) OVER (PARTITION BY i ORDER BY v, j) AS a3
FROM a WINDOW w AS (PARTITION BY i ORDER BY v)""")
def o_rank_forms(s, d):
    """Ranks within every row of the matrix."""
    by_value, one_by_one = Window.partitionBy("i").orderBy("v"), Window.partitionBy("i").orderBy("v", "j")
    forms = F.rank().over(by_value), F.dense_rank().over(by_value), F.ntile(4).over(one_by_one)
    return fold_pair(s, d)[0].select("i", "j", *(f.cast("long").alias(f"a{k + 1}") for k, f in enumerate(forms)))


@query("o_rank_shares", _A + """SELECT i, j, round(percent_rank() OVER w, 9) AS percent, round(cume_dist() OVER w, 9) AS share,
first_value(j) OVER x AS low, last_value(j) OVER x AS high, nth_value(j, 2) OVER x AS second
FROM a WINDOW w AS (PARTITION BY i ORDER BY v), x AS (PARTITION BY i ORDER BY v, j ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def o_rank_shares(s, d):
    """Relative ranks, and the first, last and second column by value, within every row."""
    w = Window.partitionBy("i").orderBy("v")
    x = Window.partitionBy("i").orderBy("v", "j").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    shares = F.round(F.percent_rank().over(w), 9).alias("percent"), F.round(F.cume_dist().over(w), 9).alias("share")
    return fold_pair(s, d)[0].select("i", "j", *shares, F.first("j").over(x).alias("low"), F.last("j").over(x).alias("high"), F.nth_value("j", 2).over(x).alias("second"))


@query("o_lag_pairs", """SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION
BY user_id ORDER BY ts, event_id)""")
def o_lag_pairs(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(s, d, "events", "event_id", "user_id", "ts", "event_type")
    return e.select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"))


@query("o_cum_row", _A + "SELECT i, j, CAST(sum(v) OVER (PARTITION BY i ORDER BY j) AS BIGINT) AS v FROM a")
def o_cum_row(s, d):
    return fold_pair(s, d)[0].select("i", "j", F.sum("v").over(Window.partitionBy("i").orderBy("j").rowsBetween(Window.unboundedPreceding, 0)).alias("v"))


@query("o_range_frame", _A + """SELECT i, j, CAST(sum(v) OVER (PARTITION BY i ORDER BY j RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS v
FROM a""")
def o_range_frame(s, d):
    return fold_pair(s, d)[0].select("i", "j", F.sum("v").over(Window.partitionBy("i").orderBy("j").rangeBetween(-2, 2)).alias("v"))


@query("o_topk", f"WITH {EMBED_SQL} SELECT * FROM m ORDER BY v DESC, i, j LIMIT 20")
def o_topk(s, d):
    return embedding_cells(s, d).orderBy(F.desc("v"), "i", "j").limit(20)


@query("o_sort", _A + "SELECT * FROM a ORDER BY i, j")
def o_sort(s, d):
    return fold_pair(s, d)[0].orderBy("i", "j")


@query("o_sort_within", _A + "SELECT i, j, v, row_number() OVER (PARTITION BY i ORDER BY v, j) AS r FROM a")
def o_sort_within(s, d):
    """Rows of the matrix side by side, each sorted in its own task; the window needs no further sort or shuffle."""
    a = fold_pair(s, d)[0].repartition("i").sortWithinPartitions("i", "v", "j")
    return a.withColumn("r", F.row_number().over(Window.partitionBy("i").orderBy("v", "j")).cast("long"))


@query("o_union", _A + "SELECT i, j FROM a UNION SELECT i, j FROM b")
def o_union(s, d):
    a, b, _ = fold_pair(s, d)
    return a.select("i", "j").union(b.select("i", "j")).distinct()


@query("o_intersect", _A + "SELECT i, j FROM a INTERSECT SELECT i, j FROM b")
def o_intersect(s, d):
    a, b, _ = fold_pair(s, d)
    return a.select("i", "j").intersect(b.select("i", "j"))


@query("o_except", _A + "SELECT i, j FROM a EXCEPT SELECT i, j FROM b")
def o_except(s, d):
    a, b, _ = fold_pair(s, d)
    return a.select("i", "j").subtract(b.select("i", "j"))


@query("o_intersect_all", "SELECT l_suppkey FROM lineitem WHERE l_quantity > 40 INTERSECT ALL SELECT l_suppkey FROM lineitem WHERE l_discount > 0.05")
def o_intersect_all(s, d):
    li = table(s, d, "lineitem", "l_suppkey", "l_quantity", "l_discount")
    return li.where("l_quantity > 40").select("l_suppkey").intersectAll(li.where("l_discount > 0.05").select("l_suppkey"))


@query("o_except_all", "SELECT l_suppkey FROM lineitem WHERE l_discount > 0.05 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_quantity > 40")
def o_except_all(s, d):
    li = table(s, d, "lineitem", "l_suppkey", "l_quantity", "l_discount")
    return li.where("l_discount > 0.05").select("l_suppkey").exceptAll(li.where("l_quantity > 40").select("l_suppkey"))


@query("o_index", """SELECT p_brand AS key, row_number() OVER (ORDER BY p_brand) - 1 AS idx FROM (SELECT DISTINCT p_brand FROM part)""")
def o_index(s, d):
    return rel.index_keys(table(s, d, "part", "p_brand"), "p_brand")


@query("o_onehot", "SELECT doc_id AS i, CAST(2 * quality + toxic AS BIGINT) AS j, CAST(1 AS BIGINT) AS v FROM labels")
def o_onehot(s, d):
    return (
        table(s, d, "labels")
        .select(F.col("doc_id").alias("i"), (2 * F.col("quality") + F.col("toxic")).cast("long").alias("j"), F.lit(1).cast("long").alias("v"))
    )


@query("o_incidence", "SELECT DISTINCT l_orderkey AS i, l_suppkey AS j FROM lineitem")
def o_incidence(s, d):
    return table(s, d, "lineitem", F.col("l_orderkey").alias("i"), F.col("l_suppkey").alias("j")).distinct()


@query("o_map_case", """SELECT event_id, CASE WHEN value > 50 THEN 'high' WHEN value > 10 THEN 'mid' ELSE 'low' END AS class, coalesce(value,
0) AS v FROM events""")
def o_map_case(s, d):
    return (
        table(s, d, "events")
        .select("event_id", F.when(F.col("value") > 50, "high").when(F.col("value") > 10, "mid").otherwise("low").alias("class"), F.coalesce("value", F.lit(0.0)).alias("v"))
    )


@query("o_string_key", """SELECT doc_id, upper(lang) || '-' || source AS key, length(text) AS n, substr(text, 1, 3) AS head FROM documents""")
def o_string_key(s, d):
    return (
        table(s, d, "documents")
        .select("doc_id", F.concat_ws("-", F.upper("lang"), "source").alias("key"), F.length("text").cast("long").alias("n"), F.substring("text", 1, 3).alias("head"))
    )


@query("o_string_parts", """SELECT p_partkey, lower(trim(p_name)) AS name, string_split(p_type, ' ')[1] AS head, regexp_replace(p_brand, '[^0-9]', '', 'g') AS digits,
reverse(p_brand) AS turned, lpad(CAST(p_size AS VARCHAR), 4, '0') AS size FROM part""")
def o_string_parts(s, d):
    p = table(s, d, "part", "p_partkey", "p_name", "p_type", "p_brand", "p_size")
    forms = F.lower(F.trim("p_name")).alias("name"), F.element_at(F.split("p_type", " "), 1).alias("head"), F.regexp_replace("p_brand", "[^0-9]", "").alias("digits")
    return p.select("p_partkey", *forms, F.reverse("p_brand").alias("turned"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("size"))


@query("o_regexp", f"SELECT page_id, {_HOST} AS host, len(regexp_extract_all(html, '<p')) AS n FROM pages")
def o_regexp(s, d):
    return (
        table(s, d, "pages")
        .select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.regexp_count("html", F.lit("<p")).cast("long").alias("n"))
    )


@query("o_date_matrix", """SELECT CAST(year(o_orderdate) AS BIGINT) AS i, CAST(month(o_orderdate) AS BIGINT) AS j, count(*) AS v FROM orders
GROUP BY 1, 2""")
def o_date_matrix(s, d):
    return cells_from(table(s, d, "orders", "o_orderdate"), F.year("o_orderdate"), F.month("o_orderdate"), F.lit(1))


@query("o_date_parts", """SELECT o_orderkey, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS weekday, CAST(hour(o_orderdate) AS INTEGER) AS hour,
CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(o_orderdate AS DATE) + 30 AS due, quarter(o_orderdate) AS quarter FROM orders""")
def o_date_parts(s, d):
    day, start = F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")
    parts = F.dayofweek(day).alias("weekday"), F.hour("o_orderdate").alias("hour"), F.datediff(day, start).alias("days"), F.date_add(day, 30).cast("timestamp").alias("due")
    return table(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", *parts, F.quarter(day).cast("long").alias("quarter"))


@query("o_math", """SELECT k, round(log2(k), 6) AS a, round(sqrt(k), 6) AS b, ceil(k / 3.0) AS c, (k % 7) AS d
FROM (SELECT unnest(range(1, 200)) AS k)""")
def o_math(s, d):
    k = F.col("id")
    forms = F.round(F.log2(k), 6).alias("a"), F.round(F.sqrt(k), 6).alias("b"), F.ceil(k / 3.0).cast("double").alias("c"), F.pmod(k, F.lit(7)).alias("d")
    return s.range(1, 200).select(k.alias("k"), *forms)


@query("o_array", """SELECT vec_id, len(embedding) AS n, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top, len(list_filter(embedding,
lambda x: x > 0)) AS positive FROM embeddings""")
def o_array(s, d):
    top = F.round(F.array_max("embedding").cast("double"), 6)
    positive = F.size(F.filter("embedding", lambda x: x > 0)).cast("long")
    return table(s, d, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), top.alias("top"), positive.alias("positive"))


@query("o_json_key", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def o_json_key(s, d):
    return table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("o_map_key", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS k FROM events")
def o_map_key(s, d):
    return (
        table(s, d, "events")
        .select("event_id", F.pmod(F.element_at(F.from_json("props", "map<string,bigint>"), "k"), F.lit(10)).alias("k"))
    )


@query("o_udaf", _A + "SELECT i, round(sqrt(sum(v * v)), 6) AS f FROM a GROUP BY 1")
def o_udaf(s, d):
    return fold_pair(s, d)[0].groupBy("i").agg(frobenius_udaf()(F.col("v").cast("double")).alias("f"))


@query("o_slice_tiles", _A + "SELECT a.* FROM a, n WHERE a.i >= n.n // 4 AND a.i < n.n // 2 + 3 AND a.j < n.n // 3")
def o_slice_tiles(s, d):
    """A slice of a tile matrix: tiles off the slice are filtered by their keys before any is opened."""
    a, _ = fold_tiles(s, d)
    return as_cells(tiles_to_cells(slice_tiles(a, (a.n_rows // 4, a.n_rows // 2 + 3), (0, a.n_cols // 3))))


@query("o_udf_gemm", _A + """, t AS (SELECT n, CASE n WHEN 56 THEN 7 WHEN 224 THEN 28 ELSE 84 END AS t FROM n)
SELECT x.i AS i, y.j AS j, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM a x JOIN b y ON x.j = y.i JOIN t ON true
WHERE x.i // t = y.i // t AND y.j // t = y.i // t AND x.j // t = x.i // t GROUP BY 1, 2 HAVING sum(x.v * y.v) <> 0""")
def o_udf_gemm(s, d):
    """The vectorised function itself: products of the tiles on the two diagonals."""
    a, b = fold_tiles(s, d)
    x, y = (m.df.where("bi = bj").select("bi", "bj", F.col("vals").alias(name)) for m, name in ((a, "x"), (b, "y")))
    return as_cells(tiles_to_cells(a.with_df(x.join(y, ["bi", "bj"]).select("bi", "bj", tile_gemm(a.tile, a.dtype)("x", "y").alias("vals")))))


query("o_approx_distinct")(lambda s, d: table(s, d, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("n")))
for _kind in ("rollup", "cube"):
    query(f"o_{_kind}", f"SELECT r_name, n_name, count(*) AS v, CAST(grouping_id(r_name, n_name) AS BIGINT) AS level FROM nation JOIN region ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey GROUP BY {_kind}(r_name, n_name)")(lambda s, d, k=_kind: rel.block_totals(table(s, d, "nation").join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).join(table(s, d, "customer", "c_nationkey"), F.col("c_nationkey") == F.col("n_nationkey")), ["r_name", "n_name"], F.lit(1), k))


@query("o_udtf", "SELECT * FROM (VALUES (1, 'S', CAST(224 AS BIGINT), CAST(49 AS BIGINT), CAST(0 AS DOUBLE), CAST(0 AS BIGINT)), (2, 'W', 112, 49, 2304, 36), (3, 'W', 56, 7, 4032, 36)) AS q(step, letter, n, workers, words, messages)")
def o_udtf(spark, d):
    register(spark)
    return spark.sql("SELECT * FROM schedule_steps('SWW', 224, 49)")


@query("o_tile_roundtrip", _A + """, t AS (SELECT CASE n WHEN 56 THEN 7 WHEN 224 THEN 28 ELSE 84 END AS t FROM n)
SELECT i, j, v FROM a, t WHERE i >= 2 * t AND i < 5 * t""")
def o_tile_roundtrip(spark, d):
    m = fold_tiles(spark, d)[0]
    path = f"{shared_folder(spark)}/tiles-{uuid.uuid4().hex}"
    write_tiles(m, path)
    return as_cells(tiles_to_cells(read_tiles(spark, path, m, (2, 5))))


def _text_cells(spark, d, kind):
    path = f"{shared_folder(spark)}/cells-{uuid.uuid4().hex}"
    getattr(trade(spark, d).write, kind)(path)
    return getattr(spark.read.schema("i long, j long, v long"), kind)(path)


@query("o_udtf_quadrants", "SELECT bi, bj, CAST(2 * (bi // 4) + bj // 4 AS INTEGER) AS quadrant, CAST(bi % 4 AS INTEGER) AS row, CAST(bj % 4 AS INTEGER) AS col FROM (SELECT CAST(unnest(range(0, 8)) AS INTEGER) AS bi), (SELECT CAST(unnest(range(0, 8)) AS INTEGER) AS bj)")
def o_udtf_quadrants(s, d):
    """A table function over the tiles of a grid, by a lateral join in SQL."""
    register(s)
    s.range(64).selectExpr("cast(id div 8 AS int) AS bi", "cast(id % 8 AS int) AS bj").createOrReplaceTempView("sevenfold_places")
    return s.sql("SELECT p.bi, p.bj, q.quadrant, q.row, q.col FROM sevenfold_places p, LATERAL quadrant_of(p.bi, p.bj, 8) q")


@query("o_sql_views", _A + "SELECT a.i AS i, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM a JOIN b ON a.j = b.i WHERE b.j = 0 GROUP BY 1")
def o_sql_views(s, d):
    """The matrices as views, queried by SQL."""
    a, b, _ = fold_pair(s, d)
    a.createOrReplaceTempView("sevenfold_a")
    b.createOrReplaceTempView("sevenfold_b")
    return s.sql("SELECT a.i AS i, sum(a.v * b.v) AS v FROM sevenfold_a a JOIN sevenfold_b b ON a.j = b.i WHERE b.j = 0 GROUP BY a.i")
