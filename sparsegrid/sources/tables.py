"""Reading tables, and matrices and graphs made from them."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import PLUS_TIMES, Semiring
from sparsegrid.model import Graph, SparseMatrix


def load_table(spark: SparkSession, folder: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    """A Parquet table; only the columns asked for are read."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def matrix_from_table(df: DataFrame, row: str, col: str, val: Column | None = None, n_rows: int = 1, n_cols: int = 1, semiring: Semiring = PLUS_TIMES) -> SparseMatrix:
    """Entries summed (by the semiring's plus) over the rows of a table; counts where there is no value."""
    value = F.lit(semiring.one) if val is None else val
    grouped = df.groupBy(F.col(row).alias("row"), F.col(col).alias("col")).agg(semiring.plus(value.cast(semiring.kind)).alias("val"))
    return SparseMatrix.of(grouped, n_rows, n_cols, semiring)


def matrix_from_arrays(df: DataFrame, key: str, array: str, width: int, n_rows: int = 1) -> SparseMatrix:
    """A matrix of doubles from an array column: the place in the array is the column id."""
    doubles = replace(PLUS_TIMES, name="double_plus_times", kind="double")
    return SparseMatrix.of(df.select(F.col(key).alias("row"), F.posexplode(array).alias("col", "val")), n_rows, width, doubles)


def terms_matrix(df: DataFrame, key: str, text: str) -> DataFrame:
    """(row, term, val): counts of the runs of letters, of any script, in lower-cased texts."""
    words = df.select(F.col(key).cast("bigint").alias("row"), F.explode(F.split(F.lower(text), r"[^\p{L}]+")).alias("term")).where("term <> ''")
    return words.groupBy("row", "term").agg(F.count("*").alias("val"))


def term_lengths(df: DataFrame, key: str, text: str) -> DataFrame:
    """(id, length): the Euclidean length of each line of ``terms_matrix``, or more where an id is repeated.

    Made within each row of the table, from its sorted words: no counts of terms are exchanged.
    """
    words = F.array_sort(F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != ""))
    begin = F.struct(F.lit("").alias("w"), F.lit(0).cast("bigint").alias("run"), F.lit(0).cast("bigint").alias("sum"))
    run = lambda a, w: F.when(a["w"] == w, a["run"]).otherwise(F.lit(0).cast("bigint"))
    squares = F.aggregate(words, begin, lambda a, w: F.struct(w.alias("w"), (run(a, w) + 1).alias("run"), (a["sum"] + 2 * run(a, w) + 1).alias("sum")))["sum"]
    lines = df.where(F.col(key).isNotNull()).select(F.col(key).cast("bigint").alias("id"), F.sqrt(F.coalesce(squares, F.lit(0))).alias("length"))
    return lines.groupBy("id").agg(F.sum("length").alias("length")).where("length > 0")


def links_matrix(df: DataFrame, key: str, html: str) -> DataFrame:
    """(row, link): the distinct targets of site-relative links in pages."""
    return df.select(F.col(key).cast("bigint").alias("row"), F.explode(F.regexp_extract_all(html, F.lit('href="/([^"]+)"'), F.lit(1))).alias("link")).distinct()


def numbered(df: DataFrame, key: str) -> DataFrame:
    """(key, id): the distinct values of a column with 60-bit hashed ids, so no order over all values is needed."""
    return df.select(key).distinct().select(key, hashed_id(F.col(key)).alias("id"))


def hashed_id(value: Column) -> Column:
    """A 60-bit id for a text, which any SQL engine can compute as well: the first 15 digits of its MD5."""
    return F.conv(F.substring(F.md5(value.cast("binary")), 1, 15), 16, 10).cast("bigint")


def graph_from_cooccurrence(df: DataFrame, group: str, item: str, n: int) -> Graph:
    """Items that share a group; repeated items of a group are one before the self-join."""
    one = df.select(group, item).distinct()
    pairs = one.alias("x").join(one.alias("y"), group).where(F.col(f"x.{item}") < F.col(f"y.{item}"))
    return Graph.of(pairs.select(F.col(f"x.{item}").alias("src"), F.col(f"y.{item}").alias("dst")), n, directed=False)


def neighbours(df: DataFrame, order: Sequence[str], item: str, group: str | None = None, ranges: int | None = None) -> DataFrame:
    """(src, dst), with ``group`` in front where given: each row's item and the next row's, in order (within the group).

    The rows are dealt by ranges of the order, neighbours are taken within each
    range, and the ends of the ranges are stitched together: no window runs over
    all rows, nor over all of a group.  By default a range holds about a million
    rows, and there are as many as the session's shuffles have at least.
    """
    from sparsegrid.plans.lineage import cut_lineage

    parts = ranges or max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), df.count() >> 20)
    keyed = df.select((F.col(group) if group else F.lit(0)).alias("g"), F.struct(*([group] if group else []), *order).alias("o"), F.col(item).alias("i"))
    dealt = cut_lineage(keyed.repartitionByRange(parts, "o").withColumn("p", F.spark_partition_id()))
    within = Window.partitionBy("p").orderBy("o")
    inner = dealt.select("g", F.col("i").alias("src"), F.lead("i").over(within).alias("dst"), F.lead("g").over(within).alias("h"))
    ends = dealt.groupBy("p").agg(F.min_by(F.struct("g", "i"), "o").alias("first"), F.max_by(F.struct("g", "i"), "o").alias("last"))  # one row for each range
    follow = F.lead("first").over(Window.orderBy("p"))
    across = ends.select("last.g", F.col("last.i").alias("src"), follow["i"].alias("dst"), follow["g"].alias("h"))
    met = inner.union(across).where("g = h AND dst IS NOT NULL")
    return met.select(*([F.col("g").alias(group)] if group else []), "src", "dst")


def graph_from_sequence(df: DataFrame, order: Sequence[str], item: str, n: int, partition: Sequence[str] = (), directed: bool = True, ranges: int | None = None) -> Graph:
    """An edge from each row's item to the next row's, in order (within ``partition`` where given: groups of one task each)."""
    if partition:
        follow = F.lead(item).over(Window.partitionBy(*partition).orderBy(*order))
        pairs = df.select(F.col(item).alias("src"), follow.alias("dst")).where("dst IS NOT NULL")
        return Graph.of(pairs, n, directed)
    return Graph.of(neighbours(df, order, item, ranges=ranges), n, directed)


def links_of_sequence(df: DataFrame, order: Sequence[str], item: str, partition: Sequence[str], value: str) -> DataFrame:
    """(part, src, dst, x, y): each row's item and the next row's within ``partition``, with a value of both; no link leaves a part."""
    within = Window.partitionBy(*partition).orderBy(*order)
    part = F.xxhash64(*partition).alias("part")
    pairs = df.select(part, F.col(item).cast("bigint").alias("src"), F.lead(item).over(within).cast("bigint").alias("dst"), F.col(value).alias("x"), F.lead(value).over(within).alias("y"))
    return pairs.where("src IS NOT NULL AND dst IS NOT NULL")


def graph_from_keys(links: Sequence[tuple[DataFrame, str, str, int, int]], n: int) -> Graph:
    """An undirected graph over several kinds of ids: (table, source column, target column, source kind, target kind)."""
    shift = 10**12
    pairs = None
    for df, src, dst, ks, kd in links:
        one = df.select((F.col(src) + ks * shift).cast("bigint").alias("src"), (F.col(dst) + kd * shift).cast("bigint").alias("dst"))
        pairs = one if pairs is None else pairs.union(one)
    return Graph.of(pairs, n, directed=False)


# The views that the workloads use, by name.


def co_order(spark: SparkSession, folder: str) -> Graph:
    """Parts that share an order."""
    items = load_table(spark, folder, "lineitem", ["l_orderkey", "l_partkey"])
    return graph_from_cooccurrence(items, "l_orderkey", "l_partkey", _rows(spark, folder, "part"))


def handoff(spark: SparkSession, folder: str, event_type: str | None = None) -> Graph:
    """From the user of an event to the user of the next."""
    events = load_table(spark, folder, "events", ["ts", "event_id", "user_id", "event_type"])
    users = events.select("user_id").distinct().count()
    events = events.where(F.col("event_type") == event_type) if event_type else events
    return graph_from_sequence(events, ["ts", "event_id"], "user_id", users)


def supply(spark: SparkSession, folder: str) -> SparseMatrix:
    """Parts by suppliers, one where a supplier has delivered the part."""
    pairs = load_table(spark, folder, "lineitem", ["l_partkey", "l_suppkey"]).distinct()
    return SparseMatrix.of(pairs.select(F.col("l_partkey").alias("row"), F.col("l_suppkey").alias("col"), F.lit(1).alias("val")), _rows(spark, folder, "part"), _rows(spark, folder, "supplier"))


def quantities(spark: SparkSession, folder: str) -> SparseMatrix:
    """Parts by suppliers, with the quantity delivered in hundredths."""
    items = load_table(spark, folder, "lineitem", ["l_partkey", "l_suppkey", "l_quantity"])
    return matrix_from_table(items, "l_partkey", "l_suppkey", F.round(F.col("l_quantity") * 100), _rows(spark, folder, "part"), _rows(spark, folder, "supplier"))


def cust_supp(spark: SparkSession, folder: str) -> SparseMatrix:
    """Customers by suppliers, one where the customer has ordered from the supplier."""
    orders = load_table(spark, folder, "orders", ["o_orderkey", "o_custkey"])
    items = load_table(spark, folder, "lineitem", ["l_orderkey", "l_suppkey"])
    pairs = orders.join(items, orders["o_orderkey"] == items["l_orderkey"]).select("o_custkey", "l_suppkey").distinct()
    return SparseMatrix.of(pairs.select(F.col("o_custkey").alias("row"), F.col("l_suppkey").alias("col"), F.lit(1).alias("val")), _rows(spark, folder, "customer"), _rows(spark, folder, "supplier"))


def doc_term(spark: SparkSession, folder: str, only: DataFrame | None = None) -> SparseMatrix:
    """Documents by terms, with counts; terms have hashed ids.  With ``only`` (id) the lines of those documents, of which alone the words are taken."""
    docs = load_table(spark, folder, "documents", ["doc_id", "text"])
    if only is not None:
        docs = docs.join(only.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
    counts = terms_matrix(docs, "doc_id", "text")
    hashed = counts.select("row", hashed_id(F.col("term")).alias("col"), "val")
    return replace(SparseMatrix.of(hashed, _rows(spark, folder, "documents"), 1), wide=True)


def doc_term_pairs(spark: SparkSession, folder: str) -> DataFrame:
    """(col, row): the terms' hashed ids and the documents of ``doc_term``; an entry is repeated where a document's id is."""
    docs = load_table(spark, folder, "documents", ["doc_id", "text"]).where("doc_id IS NOT NULL")
    words = F.array_distinct(F.split(F.lower("text"), r"[^\p{L}]+"))
    terms = docs.select(F.col("doc_id").cast("bigint").alias("row"), F.explode(words).alias("term")).where("term <> ''")
    return terms.select(hashed_id(F.col("term")).alias("col"), "row")


def forest(spark: SparkSession, folder: str) -> Graph:
    """Customers and suppliers with their nations, nations with their regions."""
    customer, supplier, nation = (load_table(spark, folder, t) for t in ("customer", "supplier", "nation"))
    n = sum(_rows(spark, folder, t) for t in ("customer", "supplier", "nation", "region"))
    return graph_from_keys([(customer, "c_custkey", "c_nationkey", 1, 3), (supplier, "s_suppkey", "s_nationkey", 2, 3), (nation, "n_nationkey", "n_regionkey", 3, 4)], n)


def similar(spark: SparkSession, folder: str, least: float = 0.15) -> Graph:
    """Vectors of one label whose cosine is at least ``least``; only vectors of a label are compared."""
    e = load_table(spark, folder, "embeddings", ["vec_id", "label", "embedding"]).select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    inner = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    unit = e.withColumn("size", F.sqrt(inner(F.col("v"), F.col("v"))))
    pairs = unit.alias("x").join(unit.alias("y"), "label").where("x.vec_id < y.vec_id").where(inner(F.col("x.v"), F.col("y.v")) >= least * F.col("x.size") * F.col("y.size"))
    return Graph.of(pairs.select(F.col("x.vec_id").alias("src"), F.col("y.vec_id").alias("dst")), _rows(spark, folder, "embeddings"), directed=False)


def order_chain(spark: SparkSession, folder: str) -> Graph:
    """Consecutive orders of each customer."""
    orders = load_table(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    return graph_from_sequence(orders, ["o_orderdate", "o_orderkey"], "o_orderkey", _rows(spark, folder, "orders"), ["o_custkey"], directed=False)


def order_chain_links(spark: SparkSession, folder: str, price: Column) -> DataFrame:
    """The links of ``order_chain``, one way, with their customers as parts and a price of both orders."""
    orders = load_table(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_totalprice"]).withColumn("p", price.cast("bigint"))
    return links_of_sequence(orders, ["o_orderdate", "o_orderkey"], "o_orderkey", ["o_custkey"], "p")


def _rows(spark: SparkSession, folder: str, name: str) -> int:
    """The number of rows of a table, from Parquet's own counts."""
    return load_table(spark, folder, name).count()
