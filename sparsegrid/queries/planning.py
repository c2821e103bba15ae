"""Queries on what the planner sees and decides: profiles, splits, bands, slices, pages, ledgers and costs."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsegrid.functions.table_functions import divisor_grid
from sparsegrid.operators import multiply as mu
from sparsegrid.operators.gram import Lines
from sparsegrid.operators.loads import loads_by_dealing
from sparsegrid.operators.ranking import deal
from sparsegrid.operators.stats import nnz_profile, totals
from sparsegrid.plans import cost, ledger
from sparsegrid.plans.planner import Grid
from sparsegrid.queries.registry import CUBE_SIDE, dealt, over, query
from sparsegrid.sources import tables as src

GRID = Grid(2, 3, 4)


@query(over("supply", "SELECT u AS id, count(*) AS nz FROM supply GROUP BY 1"))
def nnz_by_row_supply(spark, folder):
    return nnz_profile(src.supply(spark, folder), "row")


@query(over("doc_term", "SELECT nz, count(*) AS terms FROM (SELECT v, count(*) AS nz FROM doc_term GROUP BY 1) GROUP BY 1"))
def nnz_by_col_doc_term(spark, folder):
    """How many terms occur in how many documents."""
    return nnz_profile(src.doc_term(spark, folder), "col").groupBy("nz").agg(F.count("*").alias("terms"))


@query(over("doc_term", "SELECT (SELECT count(*) FROM doc_term) AS nz, (SELECT CAST(sum(c * c) AS BIGINT) FROM (SELECT count(*) AS c FROM doc_term GROUP BY v)) AS products"))
def totals_doc_term(spark, folder):
    """Entries, and elementary products of the matrix with its transpose."""
    d = src.doc_term(spark, folder).cut()
    t = totals(d, d.transpose())
    return spark.range(1).select(F.lit(t.nz_s).cast("bigint").alias("nz"), F.lit(t.products).cast("bigint").alias("products"))


_SPLITS = """WITH s AS (SELECT (SELECT count(*) FROM part) AS n, (SELECT count(*) FROM co_order) AS nz),
g AS (SELECT a, b, n // (a * b) AS c, CAST(nz AS DOUBLE) * b / (CAST(n AS DOUBLE) * n) + CAST(nz AS DOUBLE) * a / (CAST(n AS DOUBLE) * n) + CAST(n AS DOUBLE) / (a * b) AS cost
  FROM s, range(1, n + 1) x(a), range(1, n + 1) y(b) WHERE n % a = 0 AND (n // a) % b = 0)"""


def _splits(spark, n: int, nz: int):
    """All grids of n workers with their costs, as a table; only divisors meet."""
    ids = spark.range(1, n + 1).where(F.lit(n) % F.col("id") == 0)
    both = ids.select(F.col("id").alias("a")).crossJoin(F.broadcast(ids.select(F.col("id").alias("b")))).where(F.lit(n) % (F.col("a") * F.col("b")) == 0)
    square, size = F.lit(float(n)) * n, F.lit(float(nz))
    return both.select("a", "b", F.floor(F.lit(n) / (F.col("a") * F.col("b"))).alias("c"), (size * F.col("b") / square + size * F.col("a") / square + F.lit(float(n)) / (F.col("a") * F.col("b"))).alias("cost"))


@query(over("co_order", _SPLITS + " SELECT a, b, c, round(cost, 6) AS cost FROM g"))
def split_candidates(spark, folder):
    g = src.co_order(spark, folder)
    return _splits(spark, g.n, g.edges.count()).withColumn("cost", F.round("cost", 6))


@query(over("co_order", _SPLITS + " SELECT a, b, c, round(cost, 6) AS cost FROM g ORDER BY g.cost, a, b LIMIT 1"))
def split_choice(spark, folder):
    """The cheapest grid of the co-order graph squared, with as many workers as parts."""
    g = src.co_order(spark, folder)
    return _splits(spark, g.n, g.edges.count()).orderBy("cost", "a", "b").limit(1).withColumn("cost", F.round("cost", 6))


@query(over("co_order", """WITH s AS (SELECT CAST((SELECT count(*) FROM part) AS DOUBLE) AS n, CAST((SELECT count(*) FROM co_order) AS DOUBLE) AS nz),
g AS (SELECT k, a, b, k // (a * b) AS c, n * n / (k * k) + nz * b / (k * k) + nz * a / (k * k) + n * n / (k * a * b) AS cost
  FROM s, (VALUES (16), (64), (512)) w(k), range(1, 513) x(a), range(1, 513) y(b) WHERE k % a = 0 AND (k // a) % b = 0 AND a * b <= k),
r AS (SELECT *, row_number() OVER (PARTITION BY k ORDER BY cost, a, b) AS i FROM g)
SELECT CAST(k AS INTEGER) AS k, CAST(a AS INTEGER) AS a, CAST(b AS INTEGER) AS b, CAST(c AS INTEGER) AS c, round(cost, 4) AS cost FROM r WHERE i = 1"""))
def split_choice_k(spark, folder):
    """The cheapest grids with 16, 64 and 512 workers."""
    from sparsegrid.plans.planner import choose_split

    g = src.co_order(spark, folder)
    nz, rows = g.edges.count(), []
    for k in (16, 64, 512):
        x = choose_split(g.n, nz, nz, k)
        rows.append((k, x.a, x.b, x.c, cost.split_cost_k(g.n, k, nz, nz, x.a, x.b)))
    return spark.createDataFrame(rows, "k int, a int, b int, c int, cost double").withColumn("cost", F.round("cost", 4))


_VIEW_SIZES = """(SELECT 'co_order' AS view, (SELECT count(*) FROM part) AS n, (SELECT count(*) FROM co_order) AS m
  UNION ALL SELECT 'handoff', (SELECT count(DISTINCT user_id) FROM events), (SELECT count(*) FROM handoff)
  UNION ALL SELECT 'handoff_purchase', (SELECT count(DISTINCT user_id) FROM events), (SELECT count(*) FROM handoff_purchase))"""


def _view_sizes(spark, folder):
    return [(name, g.n, g.edges.count()) for name, g in (("co_order", src.co_order(spark, folder)), ("handoff", src.handoff(spark, folder)), ("handoff_purchase", src.handoff(spark, folder, "purchase")))]


@query(over("co_order handoff handoff_purchase", f"""SELECT view, n, m, round(pow(m, 2.0 / 3) / n + 1, 4) AS product, round(pow(m / n, 1.0 / 3) + 1, 4) AS one_sparse, round(m / pow(n, 5.0 / 3) + 1, 4) AS triangles,
  round(pow(n, 1.0 / 3), 4) AS dense, round(pow(n, 1 - 2 / 2.3728639), 4) AS ring, round(CAST(m AS DOUBLE) * m / (CAST(n AS DOUBLE) * n * n), 4) AS arboricity_floor FROM {_VIEW_SIZES}"""))
def cost_table(spark, folder):
    """Predicted rounds of the methods and baselines on the views."""
    rows = [(v, n, m, cost.rounds_equal_sparsity(n, m), cost.rounds_one_sparse(n, m), cost.rounds_triangles(n, m), cost.rounds_dense(n), cost.rounds_ring(n), cost.triangles_arboricity_floor(n, m)) for v, n, m in _view_sizes(spark, folder)]
    names = ["product", "one_sparse", "triangles", "dense", "ring", "arboricity_floor"]
    df = spark.createDataFrame(rows, "view string, n bigint, m bigint, " + ", ".join(f"{c} double" for c in names))
    return df.select("view", "n", "m", *[F.round(c, 4).alias(c) for c in names])


@query(over("co_order handoff handoff_purchase", f"""SELECT view, n, m, round(pow(n, 1.5), 2) AS four_cycles_up_to, m <= pow(n, 1.5) AS constant_rounds,
  round(pow(n, 4 - 6 / 2.3728639) / 64, 2) AS paths_below, round(pow(n, 8.0 / 3 - 2 / 2.3728639), 2) AS counting_below, m < pow(n, 8.0 / 3 - 2 / 2.3728639) AS listing_wins FROM {_VIEW_SIZES}"""))
def crossovers(spark, folder):
    """Edge counts below which the sparse methods win, with diameter 4 for paths."""
    rows = [(v, n, m, cost.crossover_four_cycles(n), m <= cost.crossover_four_cycles(n), cost.crossover_paths(n, 4), cost.crossover_counting(n), m < cost.crossover_counting(n)) for v, n, m in _view_sizes(spark, folder)]
    df = spark.createDataFrame(rows, "view string, n bigint, m bigint, four_cycles_up_to double, constant_rounds boolean, paths_below double, counting_below double, listing_wins boolean")
    for c in ("four_cycles_up_to", "paths_below", "counting_below"):
        df = df.withColumn(c, F.round(c, 2))
    return df


@query(over("co_order handoff handoff_purchase", f"""WITH s AS (SELECT * FROM {_VIEW_SIZES}), g AS (SELECT view, k, a, b, CAST(n AS DOUBLE) * n / (k * k) + CAST(m AS DOUBLE) * b / (k * k) + CAST(m AS DOUBLE) * a / (k * k) + CAST(n AS DOUBLE) * n / (k * a * b) AS cost
  FROM s, (VALUES (16), (64), (512)) w(k), range(1, 513) x(a), range(1, 513) y(b) WHERE k % a = 0 AND (k // a) % b = 0 AND a * b <= k)
SELECT view, CAST(k AS INTEGER) AS k, count(*) AS grids, round(min(cost), 4) AS best, round(max(cost), 4) AS worst FROM g GROUP BY 1, 2"""))
def split_landscape(spark, folder):
    """Best and worst grids of all views for several numbers of workers."""
    from sparsegrid.plans.planner import grids

    rows = []
    for v, n, m in _view_sizes(spark, folder):
        for k in (16, 64, 512):
            all_ = [cost.split_cost_k(n, k, m, m, g.a, g.b) for g in grids(k)]
            rows.append((v, k, len(all_), min(all_), max(all_)))
    return spark.createDataFrame(rows, "view string, k int, grids bigint, best double, worst double").withColumn("best", F.round("best", 4)).withColumn("worst", F.round("worst", 4))


@query(over("supply", f"SELECT id, nz, {dealt('id', 'nz', '8')} AS band FROM (SELECT u AS id, count(*) AS nz FROM supply GROUP BY 1)"))
def bands_supply_rows(spark, folder):
    return mu.bands(src.supply(spark, folder), "row", 8).select("id", "nz", "band")


@query(over("supply", """WITH p AS (SELECT u AS id, count(*) AS nz FROM supply GROUP BY 1), r AS (SELECT *, row_number() OVER (ORDER BY nz, id) - 1 + (8 - count(*) OVER () % 8) % 8 AS q FROM p)
SELECT id, nz, CAST(CASE WHEN (q // 8) % 2 = 0 THEN q % 8 ELSE 7 - q % 8 END AS INTEGER) AS band FROM r"""))
def bands_serpentine(spark, folder):
    return mu.bands(src.supply(spark, folder), "row", 8, "serpentine").select("id", "nz", "band")


@query(over("doc_term", f"SELECT band, count(*) AS lines, CAST(sum(nz) AS BIGINT) AS nz FROM (SELECT nz, {dealt('v', 'nz', '16')} AS band FROM (SELECT v, count(*) AS nz FROM doc_term GROUP BY 1)) GROUP BY 1"))
def bands_doc_term_cols(spark, folder):
    """Terms dealt to 16 bands; lines and entries of each."""
    return mu.bands(src.doc_term(spark, folder), "col", 16).groupBy("band").agg(F.count("*").alias("lines"), F.sum("nz").alias("nz"))


_CO_BANDS = f"WITH r AS (SELECT u AS id, count(*) AS nz FROM co_order GROUP BY 1), c AS (SELECT v AS id, count(*) AS nz FROM co_order GROUP BY 1), br AS (SELECT id, nz, {dealt('id', 'nz', '25')} AS band FROM r), bc AS (SELECT id, nz, {dealt('id', 'nz', '40')} AS band FROM c)"


@query(over("co_order", _CO_BANDS + """ SELECT *, nz <= bound AS ok FROM (
  SELECT 'S' AS side, band, CAST(sum(nz) AS BIGINT) AS nz, (SELECT count(*) FROM co_order) / 25.0::DOUBLE + (SELECT count(*) FROM part) AS bound FROM br GROUP BY band
  UNION ALL SELECT 'T', band, CAST(sum(nz) AS BIGINT), (SELECT count(*) FROM co_order) / 40.0::DOUBLE + (SELECT count(*) FROM part) FROM bc GROUP BY band)"""))
def balance_check_co_order(spark, folder):
    """Every band of a 25 x 40 grid against its bound."""
    a = src.co_order(spark, folder).cut().matrix()
    nz = a.nnz()
    plan = mu.Plan(a, a, Grid(25, 40, 2), mu.bands(a, "row", 25), mu.bands(a, "col", 40), a.df)
    return ledger.balance_check(plan, nz, nz)


@query(over("doc_term", """WITH p AS (SELECT v, count(*) AS nz FROM doc_term GROUP BY 1), c AS (SELECT CAST(ceil(sum(nz) / count(*)) AS BIGINT) AS chunk FROM p)
SELECT chunk, CAST(sum((nz + chunk - 1) // chunk) AS BIGINT) AS pieces, count(*) AS lines, sum((nz + chunk - 1) // chunk) <= 2 * count(*) AS ok FROM p, c GROUP BY chunk"""))
def slices_doc_term(spark, folder):
    """Terms cut into pieces of the mean length: at most twice as many pieces as lines."""
    profile = nnz_profile(src.doc_term(spark, folder), "col")
    r = profile.agg(F.sum("nz"), F.count("*")).first()
    chunk = max(1, -(-r[0] // r[1]))
    pieces = mu.piece_table(profile, chunk)
    return pieces.agg(F.count("*").alias("pieces"), F.countDistinct("id").alias("lines")).select(F.lit(chunk).cast("bigint").alias("chunk"), "pieces", "lines", (F.col("pieces") <= 2 * F.col("lines")).alias("ok"))


@query(over("supply", """WITH p AS (SELECT u AS id, count(*) AS nz FROM supply GROUP BY 1), q AS (SELECT *, CAST(sum((nz + 9) // 10) OVER (ORDER BY id) AS BIGINT) - (nz + 9) // 10 AS f FROM p),
s AS (SELECT id, nz, f, unnest(range(0, (nz + 9) // 10)) AS piece FROM q)
SELECT id, CAST(piece AS INTEGER) AS piece, least(10, nz - piece * 10) AS size, (f + piece) // 2 AS owner FROM s"""))
def slice_owners(spark, folder):
    """Pieces of ten entries of every part's line, and their owners."""
    return mu.piece_table(nnz_profile(src.supply(spark, folder), "row"), 10)


@query(over("supply", "SELECT piece, count(*) AS entries FROM (SELECT CAST((row_number() OVER (PARTITION BY v ORDER BY u) - 1) // 100 AS INTEGER) AS piece FROM supply) GROUP BY 1"))
def sliced_lines_supply(spark, folder):
    """Suppliers' lines cut into pieces of a hundred entries; entries by piece number."""
    return mu.slice_lines(src.supply(spark, folder), "col", 100).groupBy("piece").agg(F.count("*").alias("entries"))


_HO_PAGES = f"""WITH br AS (SELECT id, {dealt('id', 'nz', '2')} AS band FROM (SELECT u AS id, count(*) AS nz FROM handoff GROUP BY 1)), bc AS (SELECT id, {dealt('id', 'nz', '3')} AS band FROM (SELECT v AS id, count(*) AS nz FROM handoff GROUP BY 1)),
ws AS (SELECT band AS bi, v AS page, count(*) AS ws FROM handoff JOIN br ON br.id = u GROUP BY 1, 2), wt AS (SELECT band AS bj, u AS page, count(*) AS wt FROM handoff JOIN bc ON bc.id = v GROUP BY 1, 2),
pg AS (SELECT bi, bj, page, ws, wt, ws + wt AS w FROM ws JOIN wt USING (page)),
asg AS (SELECT *, {dealt('page', 'w', '4', 'bi, bj')} AS slot FROM pg)"""


def _handoff_plan(spark, folder):
    a = src.handoff(spark, folder).cut().matrix()
    return mu.plan_product(a, a, GRID)


@query(over("handoff", _HO_PAGES + " SELECT bi, bj, page, ws, wt, w FROM pg"))
def page_weights_handoff(spark, folder):
    plan = _handoff_plan(spark, folder)
    return mu.page_weights(plan.s, plan.t, plan.bands_s, plan.bands_t)


@query(over("handoff", _HO_PAGES + " SELECT bi, bj, page, w, slot, CAST((bi * 3 + bj) * 4 + slot AS INTEGER) AS worker FROM asg"))
def page_assignment_handoff(spark, folder):
    return _handoff_plan(spark, folder).pages.select("bi", "bj", "page", "w", "slot", "worker")


@query(over("handoff", _HO_PAGES + """, l AS (SELECT bi, bj, slot, count(*) AS pages, CAST(sum(w) AS BIGINT) AS received, CAST(sum(ws * wt) AS BIGINT) AS products FROM asg GROUP BY 1, 2, 3)
SELECT *, received <= bound AS ok FROM (SELECT *, sum(received) OVER (PARTITION BY bi, bj) / 4.0::DOUBLE + 2.0 * (SELECT count(DISTINCT user_id) FROM events) AS bound FROM l)"""))
def page_loads(spark, folder):
    return ledger.page_loads(_handoff_plan(spark, folder))


@query(over("handoff", _HO_PAGES + " SELECT CAST((bi * 3 + bj) * 4 + slot AS INTEGER) AS worker, CAST(sum(ws) AS BIGINT) AS s, CAST(sum(wt) AS BIGINT) AS t FROM asg GROUP BY 1"))
def routed_entries_count(spark, folder):
    """Entries that reach each worker, counted on the routed entries themselves."""
    s, t = mu.route_entries(_handoff_plan(spark, folder))
    both = s.groupBy("worker").agg(F.count("*").alias("s")).join(t.groupBy("worker").agg(F.count("*").alias("t")), "worker", "full")
    return both.select("worker", "s", "t")


@query(over("handoff", _HO_PAGES + ", a AS (SELECT CAST((bi * 3 + bj) * 4 + slot AS INTEGER) AS worker, * FROM asg) SELECT phase, worker, CAST(received AS BIGINT) AS received FROM (SELECT 'requests' AS phase, worker, count(*) AS received FROM a GROUP BY worker UNION ALL SELECT 'deliver_s', worker, sum(ws) FROM a GROUP BY worker UNION ALL SELECT 'deliver_t', worker, sum(wt) FROM a GROUP BY worker)"))
def ledger_multiply(spark, folder):
    plan = _handoff_plan(spark, folder)
    nz = plan.s.nnz()
    return ledger.product_ledger(plan, nz, nz)


@query(over("handoff", """WITH s AS (SELECT (SELECT count(DISTINCT user_id) FROM events) AS n, (SELECT count(*) FROM handoff) AS nz)
SELECT phase, CAST(messages AS BIGINT) AS messages FROM (SELECT 'transpose_t' AS phase, nz AS messages FROM s UNION ALL SELECT 'announce_nz', 2 * n * (n - 1) FROM s UNION ALL SELECT 'permute', 3 * nz FROM s UNION ALL SELECT 'columns_s', nz FROM s
  UNION ALL SELECT 'announce_lines', 2 * n * (n - 1) FROM s UNION ALL SELECT 'slices', 2 * nz FROM s UNION ALL SELECT 'band_counts', 4 * n * n FROM s UNION ALL SELECT 'assemble_bound', n * n * n // 6 FROM s)"""))
def ledger_fixed_phases(spark, folder):
    a = src.handoff(spark, folder).cut().matrix()
    nz = a.nnz()
    return spark.createDataFrame([(p, m) for p, m, _ in ledger.fixed_phases(a.n, nz, nz, 6)], "phase string, messages bigint")


def _skew(plan):
    of = plan.pages.groupBy("worker").agg(F.sum("w").alias("w"), F.sum(F.col("ws") * F.col("wt")).alias("p"))
    return of.agg(F.round(F.max("w") * plan.grid.workers / F.sum("w"), 3).alias("messages"), F.round(F.max("p") * plan.grid.workers / F.sum("p"), 3).alias("products"))


def _largest(loads, workers):
    """The same from the loads of blocks on and above the diagonal, which those below repeat."""
    skew = lambda c, name: F.round(F.max(c) * workers / F.sum(F.when(F.col("bi") < F.col("bj"), 2 * F.col(c)).otherwise(F.col(c))), 3).alias(name)
    return loads.agg(skew("w", "messages"), skew("p", "products"))


_TERMS = "WITH t AS MATERIALIZED (SELECT u, CAST('0x' || substr(md5(v), 1, 15) AS BIGINT) AS v FROM doc_term), pr AS (SELECT u AS id, count(*) AS nz FROM t GROUP BY 1)"
_RANGE = "CAST((row_number() OVER (PARTITION BY {0} ORDER BY {1}) - 1) * 4 // count(*) OVER (PARTITION BY {0}) AS INTEGER)"


def _ablated(name: str, bands: str, slots: str) -> str:
    """One variant of the dealing, as common table expressions and a row."""
    return f""", b{name} AS (SELECT id, {bands} AS band FROM pr), s{name} AS (SELECT band AS bi, v AS page, count(*) AS ws FROM t JOIN b{name} ON id = u GROUP BY 1, 2),
g{name} AS (SELECT bi, bj, page, coalesce(ws, 0) AS ws, coalesce(wt, 0) AS wt, coalesce(ws, 0) + coalesce(wt, 0) AS w FROM (SELECT bi, page, ws, bj FROM s{name}, range(0, 4) r(bj)) FULL JOIN (SELECT bi AS bj, page, ws AS wt, q AS bi FROM s{name}, range(0, 4) r(q)) USING (bi, bj, page)),
w{name} AS (SELECT sum(w) AS w, sum(ws * wt) AS p FROM (SELECT *, {slots} AS slot FROM g{name}) GROUP BY bi, bj, slot), r{name} AS (SELECT round(max(w) * 64 / sum(w), 3) AS messages, round(max(p) * 64 / sum(p), 3) AS products FROM w{name})"""


_DEALT_B, _DEALT_P = dealt("id", "nz", "4"), dealt("page", "w", "4", "bi, bj")
_NEXT_B, _NEXT_P = "CAST((row_number() OVER (ORDER BY id) - 1) * 4 // count(*) OVER () AS INTEGER)", _RANGE.format("bi, bj", "page")
_VARIANTS = (("full", _DEALT_B, _DEALT_P), ("bands", _NEXT_B, _DEALT_P), ("pages", _DEALT_B, _NEXT_P), ("neither", _NEXT_B, _NEXT_P))


@query(over("doc_term", _TERMS + "".join(_ablated(*v) for v in _VARIANTS) + " SELECT 'full' AS variant, * FROM rfull UNION ALL SELECT 'adjacent bands', * FROM rbands UNION ALL SELECT 'adjacent pages', * FROM rpages UNION ALL SELECT 'neither', * FROM rneither"))
def ablation_doc_term(spark, folder):
    """Largest over mean intake on the 4 x 4 x 4 grid of documents by terms, with and without each balancing step."""
    loads, d, out = loads_by_dealing(Lines.of(src.doc_term_pairs(spark, folder), both=False), 4), None, None
    for name, bands, pages in (("full", "stride", "stride"), ("adjacent bands", "adjacent", "stride"), ("adjacent pages", "stride", "ranges"), ("neither", "adjacent", "ranges")):
        if loads is None:
            d = d or src.doc_term(spark, folder).cut()
            row = _skew(mu.plan_product(d, d.transpose(), Grid(4, 4, 4), bands, pages, keep_idle=True))
        else:
            row = _largest(loads.where((F.col("bands") == bands) & (F.col("pages") == pages)), 64)
        row = row.select(F.lit(name).alias("variant"), "messages", "products")
        out = row if out is None else out.union(row)
    return out


@query()
def ablation_random_bands(spark, folder):
    """The same with bands by a seeded hash, which SQL engines do not share."""
    d = src.doc_term(spark, folder).cut()
    return _skew(mu.plan_product(d, d.transpose(), Grid(4, 4, 4), "random", "ranges", keep_idle=True))


@query(over("doc_term", _TERMS + """, l AS (SELECT v AS id, count(*) AS nz FROM t GROUP BY 1), c AS (SELECT CAST(ceil(sum(nz) / count(*)) AS BIGINT) AS c FROM l),
q AS (SELECT nz, c, CAST(sum((nz + c - 1) // c) OVER (ORDER BY id) AS BIGINT) - (nz + c - 1) // c AS f, row_number() OVER (ORDER BY id) - 1 AS rank FROM l, c),
pc AS (SELECT ((f + i) // 2) % 64 AS worker, sum(least(c, nz - i * c)) * 8 AS sent FROM (SELECT *, unnest(range(0, (nz + c - 1) // c)) AS i FROM q) GROUP BY 1),
wl AS (SELECT rank % 64 AS worker, sum(nz) * 8 AS sent FROM q GROUP BY 1)
SELECT 'pieces' AS senders, round(max(sent) * 64 / sum(sent), 3) AS skew FROM pc UNION ALL SELECT 'whole lines', round(max(sent) * 64 / sum(sent), 3) FROM wl"""))
def ablation_senders_doc_term(spark, folder):
    """Largest over mean number of entries that an owner sends: lines held in pieces of the mean length, and whole lines."""
    d = src.doc_term(spark, folder).cut()
    r = nnz_profile(d, "col").agg(F.sum("nz"), F.count("*")).first()
    out = None
    for name, chunk in (("pieces", max(1, -(-r[0] // r[1]))), ("whole lines", None)):
        loads = ledger.sender_loads(d, d.transpose(), Grid(4, 4, 4), chunk)
        row = loads.agg(F.round(F.max("sent") * 64 / F.sum("sent"), 3).alias("skew")).select(F.lit(name).alias("senders"), "skew")
        out = row if out is None else out.union(row)
    return out


@query(over("co_order handoff handoff_purchase", f"SELECT view, round(pow(n, 1.0 / 3), 4) AS floor, m >= CAST(n AS DOUBLE) * (n - 1) / 2 AS dense FROM {_VIEW_SIZES}"))
def listing_floor(spark, folder):
    """The lower bound on listing triangles that holds for dense graphs, and which views are dense."""
    rows = [(v, cost.rounds_listing_floor(n), m >= n * (n - 1) / 2) for v, n, m in _view_sizes(spark, folder)]
    return spark.createDataFrame(rows, "view string, floor double, dense boolean").withColumn("floor", F.round("floor", 4))


@query("SELECT k, CAST(a AS INTEGER) AS a, CAST(b AS INTEGER) AS b, CAST(k // (a * b) AS INTEGER) AS c FROM (SELECT DISTINCT p_size AS k FROM part WHERE p_size >= 1), range(1, (SELECT max(p_size) + 1 FROM part)) x(a), range(1, (SELECT max(p_size) + 1 FROM part)) y(b) WHERE k % a = 0 AND (k // a) % b = 0")
def udtf_divisor_grid(spark, folder):
    """All grids of as many workers as a part's size says, for every size in use."""
    sizes = src.load_table(spark, folder, "part", ["p_size"]).where("p_size >= 1").select(F.col("p_size").alias("k")).distinct()
    return sizes.lateralJoin(divisor_grid(F.col("k").outer())).select("k", "a", "b", "c")


@query(over("handoff", f"""WITH s AS (SELECT (SELECT count(DISTINCT user_id) FROM events) AS n0, (SELECT count(*) FROM handoff) AS m), p AS (SELECT m, {CUBE_SIDE.format("n0")} AS p FROM s)
SELECT CAST(p AS INTEGER) AS p, m, round(m / CAST(p AS DOUBLE) + p * p * p, 4) AS alpha, round(m / CAST(p * p AS DOUBLE) + p * p * p, 4) AS beta FROM p"""))
def tri_alpha_beta(spark, folder):
    from sparsegrid.operators.triangles import side_of

    g = src.handoff(spark, folder)
    m, p = g.edges.count(), side_of(g.n)
    return spark.createDataFrame([(p, m, round(cost.listing_alpha(p**3, m), 4), round(cost.listing_beta(p**3, m), 4))], "p int, m bigint, alpha double, beta double")


@query(over("handoff", _HO_PAGES + """, l AS (SELECT CAST(sum(w) AS BIGINT) AS w FROM asg GROUP BY bi, bj, slot),
z AS (SELECT (SELECT count(*) FROM handoff) AS nz, (SELECT count(DISTINCT user_id) FROM events) AS n)
SELECT most, round(mean, 6) AS mean, bound, most <= bound AS ok FROM (SELECT max(w) AS most, sum(w) / 24.0::DOUBLE AS mean, any_value(nz) * 3 / 24.0::DOUBLE + any_value(nz) * 2 / 24.0::DOUBLE + 6 * any_value(n) AS bound FROM l, z)"""))
def intake_handoff(spark, folder):
    """The largest and the mean intake of a worker, and the bound."""
    plan = _handoff_plan(spark, folder)
    nz = plan.s.nnz()
    return ledger.intake_report(plan, nz, nz).select("most", F.round("mean", 6).alias("mean"), "bound", "ok")


@query(over("handoff", _HO_PAGES + """, z AS (SELECT (SELECT count(*) FROM handoff) AS nz, (SELECT count(DISTINCT user_id) FROM events) AS n)
SELECT *, received <= bound AS ok FROM (SELECT bi, bj, CAST(sum(w) AS BIGINT) AS received, any_value(nz) / 2.0::DOUBLE + any_value(nz) / 3.0::DOUBLE + 2 * any_value(n) AS bound FROM asg, z GROUP BY bi, bj)"""))
def ledger_block_intake(spark, folder):
    """What the workers of each block receive together, against its bound."""
    plan = _handoff_plan(spark, folder)
    nz = plan.s.nnz()
    return ledger.block_intake(plan, nz, nz)


_MESSAGES = _HO_PAGES + """, wk AS (SELECT *, (bi * 3 + bj) * 4 + slot AS worker FROM asg),
qs AS (SELECT page, CAST(sum((nz + 19) // 20) OVER (ORDER BY page) AS BIGINT) - (nz + 19) // 20 AS f, (nz + 19) // 20 AS c FROM (SELECT v AS page, count(*) AS nz FROM handoff GROUP BY 1)),
qt AS (SELECT page, CAST(sum((nz + 19) // 20) OVER (ORDER BY page) AS BIGINT) - (nz + 19) // 20 AS f, (nz + 19) // 20 AS c FROM (SELECT u AS page, count(*) AS nz FROM handoff GROUP BY 1)),
es AS (SELECT br.band AS bi, v AS page, (row_number() OVER (PARTITION BY v ORDER BY u) - 1) // 20 AS piece FROM handoff JOIN br ON br.id = u),
et AS (SELECT bc.band AS bj, u AS page, (row_number() OVER (PARTITION BY u ORDER BY v) - 1) // 20 AS piece FROM handoff JOIN bc ON bc.id = v),
mv AS (SELECT 'deliver_s' AS phase, (f + piece) // 2 % 24 AS a, worker AS b FROM es JOIN qs USING (page) JOIN wk USING (bi, page)
  UNION ALL SELECT 'deliver_t', (f + piece) // 2 % 24, worker FROM et JOIN qt USING (page) JOIN wk USING (bj, page)
  UNION ALL SELECT 'requests', worker, (f + i) // 2 % 24 FROM wk JOIN qs USING (page), range(0, 100000) r(i) WHERE i < c
  UNION ALL SELECT 'requests', worker, (f + i) // 2 % 24 FROM wk JOIN qt USING (page), range(0, 100000) r(i) WHERE i < c
  UNION ALL SELECT 'assemble', worker, row % 24 FROM (SELECT DISTINCT worker, x.u AS row, y.v AS col FROM handoff x JOIN handoff y ON x.v = y.u JOIN br ON br.id = x.u JOIN bc ON bc.id = y.v JOIN wk ON wk.page = x.v AND wk.bi = br.band AND wk.bj = bc.band)),
led AS (SELECT phase, worker, CAST(sum(s) AS BIGINT) AS sent, CAST(sum(r) AS BIGINT) AS received FROM (SELECT phase, a AS worker, 1 AS s, 0 AS r FROM mv UNION ALL SELECT phase, b, 0, 1 FROM mv) GROUP BY 1, 2)"""


@query(over("handoff", _MESSAGES + " SELECT phase, CAST(worker AS INTEGER) AS worker, sent, received FROM led"))
def ledger_sent_received(spark, folder):
    """Messages of each phase by sender and receiver; lines are held in pieces of twenty entries."""
    return ledger.message_ledger(_handoff_plan(spark, folder), 20)


@query(over("handoff", _MESSAGES + " SELECT phase, max(sent) AS most_sent, max(received) AS most_received, CAST(ceil(greatest(max(sent), max(received)) / 23.0::DOUBLE) AS BIGINT) AS rounds FROM led GROUP BY 1"))
def ledger_rounds(spark, folder):
    """Rounds that the 24 workers need for each phase."""
    return ledger.phase_rounds(ledger.message_ledger(_handoff_plan(spark, folder), 20), 24)


@query(f"SELECT r_regionkey AS id, {dealt('r_regionkey', 'w', '3')} AS band FROM (SELECT r_regionkey, length(r_name) AS w FROM region)")
def deal_regions(spark, folder):
    r = src.load_table(spark, folder, "region").select(F.col("r_regionkey").cast("bigint").alias("id"), F.length("r_name").alias("w"))
    return deal(r, "id", "w", 3).select(F.col("id").cast("int").alias("id"), "band")
