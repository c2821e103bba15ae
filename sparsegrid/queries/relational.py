"""Queries on the operators around the methods: scans, joins, aggregates, windows, sets and functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from sparsegrid.operators import algebra as al
from sparsegrid.operators import relational as rel
from sparsegrid.queries.registry import over, query
from sparsegrid.sources import tables as src

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@query(" UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_all_tables(spark, folder):
    out = None
    for t in TABLES:
        one = src.load_table(spark, folder, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


@query("SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity < 25 GROUP BY 1")
def scan_lineitem_counts(spark, folder):
    """Two columns read, the filter pushed to the scan."""
    return src.load_table(spark, folder, "lineitem", ["l_returnflag", "l_quantity"]).where("l_quantity < 25").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query(over("qty", "SELECT u AS row, v AS col, w AS val FROM qty"))
def matrix_qty(spark, folder):
    return src.quantities(spark, folder).df


@query(over("doc_term", "SELECT u AS row, count(*) AS terms, CAST(sum(w) AS BIGINT) AS words FROM doc_term GROUP BY 1"))
def matrix_doc_term(spark, folder):
    return src.terms_matrix(src.load_table(spark, folder, "documents", ["doc_id", "text"]), "doc_id", "text").groupBy("row").agg(F.count("*").alias("terms"), F.sum("val").alias("words"))


@query(over("page_link", "SELECT v AS link, count(*) AS pages FROM page_link GROUP BY 1"))
def matrix_page_link(spark, folder):
    return src.links_matrix(src.load_table(spark, folder, "pages", ["page_id", "html"]), "page_id", "html").groupBy("link").agg(F.count("*").alias("pages"))


@query(over("co_order", "SELECT u AS v, count(*) AS d FROM co_order GROUP BY 1"))
def graph_co_order_degrees(spark, folder):
    return src.co_order(spark, folder).degrees().select("v", F.col("d_out").alias("d"))


@query(over("handoff", "SELECT u AS src, v AS dst FROM handoff"))
def graph_handoff(spark, folder):
    return src.handoff(spark, folder).edges


@query(over("order_chain", "SELECT u AS src, v AS dst FROM order_chain"))
def graph_order_chain(spark, folder):
    return src.order_chain(spark, folder).edges


@query(over("forest", "SELECT u AS src, v AS dst FROM forest"))
def graph_forest(spark, folder):
    return src.forest(spark, folder).edges


_DEAR = "SELECT p_partkey FROM part WHERE p_retailprice >= (SELECT avg(p_retailprice) FROM part)"


@query(over("co_order", f"SELECT u AS src, v AS dst FROM co_order WHERE u IN ({_DEAR}) AND v IN ({_DEAR})"))
def filter_induced(spark, folder):
    """The subgraph that the parts of at least the mean price induce."""
    part = src.load_table(spark, folder, "part", ["p_partkey", "p_retailprice"])
    mean = part.agg(F.avg("p_retailprice")).first()[0]
    return rel.induced(src.co_order(spark, folder), part.where(F.col("p_retailprice") >= mean).select(F.col("p_partkey").alias("v"))).edges


@query(over("handoff", "SELECT y.u AS page, count(*) AS products FROM handoff x JOIN handoff y ON x.v = y.u GROUP BY 1"))
def join_inner_pages(spark, folder):
    """Elementary products by page."""
    e = src.handoff(spark, folder).cut().edges
    return e.alias("x").join(e.alias("y"), F.col("x.dst") == F.col("y.src")).groupBy(F.col("y.src").alias("page")).agg(F.count("*").alias("products"))


@query(over("handoff handoff_purchase", "SELECT u AS src, v AS dst FROM handoff WHERE (u, v) IN (SELECT (u, v) FROM handoff_purchase)"))
def join_semi_mask(spark, folder):
    return rel.common_edges(src.handoff(spark, folder), src.handoff(spark, folder, "purchase"))


@query(over("handoff handoff_purchase", "SELECT u AS src, v AS dst FROM handoff_purchase WHERE (u, v) NOT IN (SELECT (u, v) FROM handoff)"))
def join_anti_frontier(spark, folder):
    return rel.missing_edges(src.handoff(spark, folder, "purchase"), src.handoff(spark, folder))


@query("SELECT n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast_nation(spark, folder):
    c, n = src.load_table(spark, folder, "customer"), src.load_table(spark, folder, "nation")
    return c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).groupBy("n_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("SELECT r_regionkey, s AS slot FROM region, range(0, 4) t(s)")
def join_cross_grid(spark, folder):
    """Regions by four slots: a tiny grid without a join."""
    return src.load_table(spark, folder, "region").select("r_regionkey", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(3).cast("bigint"))).alias("slot"))


@query("SELECT b.event_id AS purchase, count(a.event_id) AS views FROM (SELECT * FROM events WHERE event_type = 'purchase') b LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') a ON a.user_id = b.user_id AND a.ts >= b.ts - INTERVAL 1 DAY AND a.ts < b.ts GROUP BY 1")
def join_range_events(spark, folder):
    """Views of the same user in the day before each purchase."""
    e = src.load_table(spark, folder, "events", ["event_id", "ts", "user_id", "event_type"])
    return rel.range_counts(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", 24 * 3600).select(F.col("event_id").alias("purchase"), F.col("n").alias("views"))


@query("SELECT b.event_id AS purchase, a.event_id AS before FROM (SELECT * FROM events WHERE event_type = 'purchase') b ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY 1, 2) a ON a.user_id = b.user_id AND a.ts < b.ts")
def join_asof_events(spark, folder):
    """The last click of the same user before each purchase."""
    e = src.load_table(spark, folder, "events", ["event_id", "ts", "user_id", "event_type"])
    return rel.asof(e.where("event_type = 'purchase'"), e.where("event_type = 'click'"), "user_id").select(F.col("event_id").alias("purchase"), F.col("before"))


@query("SELECT s_suppkey, p.l_partkey, p.n FROM supplier, LATERAL (SELECT l_partkey, count(*) AS n FROM lineitem WHERE l_suppkey = s_suppkey GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 2) p")
def topk_per_supplier(spark, folder):
    """The two parts that each supplier delivers most often (the report's length is its purpose)."""
    n = src.load_table(spark, folder, "lineitem", ["l_partkey", "l_suppkey"]).groupBy("l_suppkey", "l_partkey").agg(F.count("*").alias("n"))
    return al.top_k(n, "n", 2, per="l_suppkey", ties=["l_partkey"]).select(F.col("l_suppkey").alias("s_suppkey"), "l_partkey", "n")


@query(over("supply", "SELECT x.v AS row, y.v AS col, count(*) AS val FROM supply x JOIN supply y ON x.u = y.u AND x.v < y.v GROUP BY 1, 2 ORDER BY val DESC, row, col LIMIT 20"))
def topk_pairs(spark, folder):
    """The twenty pairs of suppliers with most parts in common (the report's length is its purpose)."""
    from sparsegrid.operators.multiply import join_multiply

    s = src.supply(spark, folder).cut()
    return al.top_k(join_multiply(s.transpose(), s).df.where("row < col"), "val", 20, ties=["row", "col"]).select("row", "col", "val")


@query(over("qty", "SELECT u AS id, CAST(sum(w) AS BIGINT) AS val FROM qty GROUP BY 1"))
def agg_row_sums(spark, folder):
    return al.row_sums(src.quantities(spark, folder))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube_loads(spark, folder):
    return src.load_table(spark, folder, "lineitem", ["l_returnflag", "l_linestatus"]).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT n_regionkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def agg_rollup_nation(spark, folder):
    c, n = src.load_table(spark, folder, "customer"), src.load_table(spark, folder, "nation")
    return c.join(n, c["c_nationkey"] == n["n_nationkey"]).rollup("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def agg_grouping_sets(spark, folder):
    o = src.load_table(spark, folder, "orders", ["o_orderstatus", "o_orderpriority"])
    sets = [[F.col("o_orderstatus")], [F.col("o_orderpriority")]]
    return o.groupingSets(sets, "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_distinct_pairs(spark, folder):
    return src.load_table(spark, folder, "lineitem", ["l_partkey", "l_suppkey"]).groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"))


@query("SELECT o_custkey, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS first, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS last FROM orders GROUP BY 1")
def agg_min_by(spark, folder):
    key = F.struct("o_orderdate", "o_orderkey")
    return src.load_table(spark, folder, "orders", ["o_custkey", "o_orderkey", "o_orderdate"]).groupBy("o_custkey").agg(F.min_by("o_orderkey", key).alias("first"), F.max_by("o_orderkey", key).alias("last"))


SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


@query("SELECT c_nationkey, " + ", ".join(f"count(*) FILTER (c_mktsegment = '{s}') AS {s.lower()}" for s in SEGMENTS) + " FROM customer GROUP BY 1")
def agg_pivot_segment(spark, folder):
    c = src.load_table(spark, folder, "customer", ["c_nationkey", "c_mktsegment"])
    wide = c.groupBy("c_nationkey").pivot("c_mktsegment", list(SEGMENTS)).agg(F.count(F.lit(1)))
    return wide.select("c_nationkey", *[F.coalesce(s, F.lit(0)).alias(s.lower()) for s in SEGMENTS])


@query("SELECT event_type, CAST(quantile_disc(value, 0.5) AS DOUBLE) AS median FROM events GROUP BY 1")
def agg_percentile(spark, folder):
    return src.load_table(spark, folder, "events", ["event_type", "value"]).groupBy("event_type").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("median"))


@query()
def agg_approx_distinct(spark, folder):
    """Sketched numbers of distinct parts, for planning only."""
    return src.load_table(spark, folder, "lineitem", ["l_partkey"]).agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts_hll"))


@query(over("supply", "SELECT u AS id, nz, row_number() OVER (ORDER BY nz, u) - 1 AS rank FROM (SELECT u, count(*) AS nz FROM supply GROUP BY 1)"))
def win_row_number_deal(spark, folder):
    """Ranks by (weight, id) as the dealing uses them, without one window over all rows."""
    from sparsegrid.operators.ranking import ranked
    from sparsegrid.operators.stats import nnz_profile

    return ranked(nnz_profile(src.supply(spark, folder), "row"), "id", "nz").select("id", "nz", F.col("rank").cast("bigint").alias("rank"))


@query("SELECT o_orderkey, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS BIGINT) AS running FROM orders")
def win_running_offset(spark, folder):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return src.load_table(spark, folder, "orders").select("o_orderkey", F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).over(w).alias("running"))


@query("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS quarter FROM customer")
def win_ntile(spark, folder):
    return src.load_table(spark, folder, "customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).cast("bigint").alias("quarter"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lead_lag(spark, folder):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return src.load_table(spark, folder, "events", ["event_id", "user_id", "ts"]).select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_moving_sum(spark, folder):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return src.load_table(spark, folder, "events", ["event_id", "user_id", "ts"]).select("event_id", F.count("*").over(w).alias("n"))


@query("SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM part")
def win_range_frame(spark, folder):
    w = Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)
    return src.load_table(spark, folder, "part", ["p_partkey", "p_brand", "p_size"]).select("p_partkey", F.count("*").over(w).alias("near"))


@query("SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS d FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size DESC)")
def win_rank_dense(spark, folder):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_size"))
    return src.load_table(spark, folder, "part", ["p_partkey", "p_brand", "p_size"]).select("p_partkey", F.rank().over(w).cast("bigint").alias("r"), F.dense_rank().over(w).cast("bigint").alias("d"))


@query("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def set_union(spark, folder):
    c, s = src.load_table(spark, folder, "customer", ["c_nationkey"]), src.load_table(spark, folder, "supplier", ["s_nationkey"])
    return c.select(F.col("c_nationkey").alias("k")).union(s).distinct()


@query("SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def set_intersect(spark, folder):
    o = src.load_table(spark, folder, "orders", ["o_custkey", "o_orderstatus"])
    return o.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("k")).intersect(o.where("o_orderstatus = 'O'").select("o_custkey"))


@query("SELECT l_suppkey AS k FROM lineitem EXCEPT ALL SELECT s_suppkey FROM supplier")
def set_except(spark, folder):
    return src.load_table(spark, folder, "lineitem", ["l_suppkey"]).select(F.col("l_suppkey").alias("k")).exceptAll(src.load_table(spark, folder, "supplier", ["s_suppkey"]))


@query("SELECT p_partkey, CAST(floor(cbrt(p_retailprice)) AS BIGINT) AS root, CAST(ceil(ln(p_retailprice)) AS BIGINT) AS log, p_partkey % 7 AS hand, p_size & 6 AS bits, greatest(p_size, 10) AS most FROM part")
def fn_math(spark, folder):
    p = src.load_table(spark, folder, "part", ["p_partkey", "p_retailprice", "p_size"])
    return p.select("p_partkey", F.floor(F.cbrt("p_retailprice")).alias("root"), F.ceil(F.log("p_retailprice")).alias("log"), F.pmod("p_partkey", F.lit(7)).alias("hand"), F.col("p_size").bitwiseAND(6).alias("bits"), F.greatest("p_size", F.lit(10)).alias("most"))


@query("SELECT page_id, lower(regexp_extract(url, '://([^/?#]+)', 1)) AS host, length(url) AS n, substr(url, 1, 8) AS head, regexp_replace(url, '[0-9]+', '#', 'g') AS masked FROM pages")
def fn_string(spark, folder):
    p = src.load_table(spark, folder, "pages", ["page_id", "url"])
    return p.select("page_id", F.lower(F.regexp_extract("url", "://([^/?#]+)", 1)).alias("host"), F.length("url").cast("bigint").alias("n"), F.substring("url", 1, 8).alias("head"), F.regexp_replace("url", "[0-9]+", "#").alias("masked"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def fn_date(spark, folder):
    o = src.load_table(spark, folder, "orders", ["o_orderkey", "o_orderdate"])
    day = F.col("o_orderdate").cast("date")
    return o.select("o_orderkey", F.year(day).cast("bigint").alias("y"), F.month(day).cast("bigint").alias("m"), F.trunc(day, "month").alias("first"), F.date_diff(day, F.lit("1995-01-01").cast("date")).cast("bigint").alias("days"))


@query("SELECT vec_id, len(embedding) AS n, CAST(list_count(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm FROM embeddings")
def fn_array(spark, folder):
    e = src.load_table(spark, folder, "embeddings", ["vec_id", "embedding"])
    norm = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return e.select("vec_id", F.size("embedding").cast("bigint").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"), F.round(norm, 4).alias("norm"))


@query(over("qty", "SELECT x.v AS a, y.v AS b, CAST(sum(x.w * y.w) AS BIGINT) AS dot FROM qty x JOIN qty y ON x.u = y.u WHERE x.v < 3 AND y.v < 3 AND x.v < y.v GROUP BY 1, 2"))
def fn_map(spark, folder):
    """Inner products of the first suppliers' lines, held as maps."""
    q = src.quantities(spark, folder).transpose()
    rows = q.df.where("row < 3").groupBy("row").agg(F.map_from_entries(F.collect_list(F.struct("col", "val"))).alias("m"))
    both = rows.alias("x").join(rows.alias("y"), F.col("x.row") < F.col("y.row"))
    dot = F.aggregate(F.map_values(F.map_zip_with("x.m", "y.m", lambda _, p, r: F.coalesce(p * r, F.lit(0)))), F.lit(0).cast("bigint"), lambda a, v: a + v)
    return both.select(F.col("x.row").alias("a"), F.col("y.row").alias("b"), dot.alias("dot")).where("dot > 0")


@query("SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k FROM events GROUP BY 1")
def fn_json(spark, folder):
    return src.load_table(spark, folder, "events", ["event_type", "props"]).groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("bigint")).alias("k"))


@query("SELECT doc_id, coalesce(l.quality, -1) AS quality, CASE WHEN l.toxic = 1 THEN 'toxic' WHEN l.toxic = 0 THEN 'clean' ELSE 'unknown' END AS mark, nullif(d.lang, 'en') AS other FROM documents d LEFT JOIN labels l USING (doc_id)")
def fn_null_case(spark, folder):
    d = src.load_table(spark, folder, "documents", ["doc_id", "lang"]).join(src.load_table(spark, folder, "labels"), "doc_id", "left")
    mark = F.when(F.col("toxic") == 1, "toxic").when(F.col("toxic") == 0, "clean").otherwise("unknown")
    return d.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), mark.alias("mark"), F.nullif("lang", F.lit("en")).alias("other"))


@query("SELECT a AS role, b AS next, count(*) AS n FROM (SELECT role AS a, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations) WHERE b IS NOT NULL GROUP BY 1, 2")
def agg_role_transitions(spark, folder):
    """How often one role follows another in conversations."""
    c = src.load_table(spark, folder, "conversations", ["conv_id", "turn", "role"])
    follow = c.select(F.col("role"), F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("next")).where("next IS NOT NULL")
    return follow.groupBy("role", "next").agg(F.count("*").alias("n"))


@query("SELECT source, toxic, count(*) AS n FROM labels JOIN documents USING (doc_id) GROUP BY 1, 2")
def agg_label_source(spark, folder):
    """The contingency table of toxicity labels and sources."""
    return src.load_table(spark, folder, "labels").join(src.load_table(spark, folder, "documents", ["doc_id", "source"]), "doc_id").groupBy("source", "toxic").agg(F.count("*").alias("n"))


@query("SELECT label, count(*) AS n, CAST(max(i) AS BIGINT) AS last FROM (SELECT label, row_number() OVER (PARTITION BY label ORDER BY vec_id) AS i FROM embeddings) GROUP BY 1")
def compact_ids_by_label(spark, folder):
    """Vectors numbered within their labels by the distributed rank."""
    from sparsegrid.operators.ranking import ranked

    e = src.load_table(spark, folder, "embeddings", ["vec_id", "label"]).withColumn("one", F.lit(1))
    return ranked(e, "vec_id", "one", ["label"]).groupBy("label").agg(F.count("*").alias("n"), (F.max("rank") + 1).alias("last"))
