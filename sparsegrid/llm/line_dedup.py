"""Line dedup by a deletion-neighbourhood join.

DataFrame functions only.  A line is its sequence of words; the distance of two
lines is the word edit distance (substitution, insertion, deletion).

Equal lines are one line, kept where it is first.  Lines are near copies when
they differ by one word in ``min_words`` at most: a shorter line has no room for
an edit and counts as equal only; of longer ones the neighbourhood of distance
one is searched:

* a line whose first or last half no other line shares has no neighbour and goes
  no further (the one edit leaves one half whole);
* of the others every variant with one word deleted is emitted as a hashed key
  with the position of the deletion, as running sums over the words, so the cost
  follows the length of the line;
* variants that are equal at the same position are substitutions, a variant that
  equals a whole line is an insertion or deletion.  The earliest line of each key
  is a minimum: no pairs within a key are listed.  Keys that very many lines
  share are minimised before they are dealt;
* the distance to that earliest line is verified on the words.

A line goes where an earlier one lies within the bound.  Places are ordered by
(doc_id, hash of the text, number of the line from 0), so rows that share an id
but not the text are rows of their own; rows of the same id and text count as one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparsegrid.plans.lineage import cut_and_release, cut_lineage, release

SPACE = r"[\x20\x09-\x0D]+"
WORDED = r"[^\x20\x09-\x0D]"
ROW = ["doc_id", "th"]
_MASK = (1 << 43) - 1  # sums of 2**20 such values stay below 2**63
_WORDS_A_TASK = 1 << 20


def words_of_line(line: Column) -> Column:
    return F.array_remove(F.split(line, SPACE), "")


def within_one_edit(a: Column, b: Column) -> Column:
    """Whether two word arrays have a word edit distance of at most one."""

    def shared(x: Column, y: Column) -> Column:
        differ = F.array_position(F.zip_with(x, y, lambda p, q: ~p.eqNullSafe(q)), True)
        return F.when(differ == 0, F.greatest(F.size(x), F.size(y))).otherwise(differ - 1)

    longer, shorter = F.greatest(F.size(a), F.size(b)), F.least(F.size(a), F.size(b))
    return (longer - shorter <= 1) & (shared(a, b) + shared(F.reverse(a), F.reverse(b)) >= longer - 1)


def _rows(docs: DataFrame) -> DataFrame:
    """(doc_id, th, text) of the rows that take part; ``th`` tells texts of one id apart."""
    return docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")


def _lines(docs: DataFrame) -> DataFrame:
    """(doc_id, th, line, words) of all lines with words."""
    one = _rows(docs).select(*ROW, F.posexplode(F.split("text", "\n")).alias("line", "body")).where(F.col("body").rlike(WORDED))
    return one.select(*ROW, "line", words_of_line(F.col("body")).alias("words"))


def _halves(words: Column, n: Column) -> Column:
    """Keys of the first and last q words, for both q that a line within one edit may use."""
    keys = []
    for q in (F.floor((n - 1) / 2).cast("int"), F.floor(n / 2).cast("int")):
        keys += [F.xxhash64(F.lit("first"), q, F.slice(words, F.lit(1), q)), F.xxhash64(F.lit("last"), q, F.slice(words, n - q + 1, q))]
    return F.array(*keys)


def _distinct_lines(docs: DataFrame, min_words: int) -> DataFrame:
    """(h1, doc_id, th, line, n, half0..half3): every distinct line where it is first; no halves for short ones."""
    words, n = F.col("words"), F.size("words")
    keyed = _lines(docs).select(F.xxhash64(words).alias("h1"), F.xxhash64(F.lit("line"), words).alias("h2"), n.alias("n"), F.struct(*ROW, "line").alias("at"), F.when(n >= min_words, _halves(words, n)).alias("halves"))
    keyed = keyed.select("h1", "h2", "n", "at", *[F.col("halves")[k].alias(f"half{k}") for k in range(4)])
    first = keyed.groupBy("h1", "h2").agg(F.min("at").alias("at"), F.min("n").alias("n"), *[F.min(f"half{k}").alias(f"half{k}") for k in range(4)])
    return first.select("h1", "at.*", "n", *[f"half{k}" for k in range(4)])


def _with_shared_half(distinct: DataFrame, many: int) -> DataFrame:
    """(ord, doc_id, th, line, n, hot): lines of which another shares a half, numbered in the order of places; ``hot`` where more than ``many`` do."""
    halves = distinct.where("half0 IS NOT NULL").select("h1", F.explode(F.array_distinct(F.array(*[f"half{k}" for k in range(4)]))).alias("half"))
    met = cut_lineage(halves.groupBy("half").agg(F.count("*").alias("k")).where("k > 1").select("half", (F.col("k") > many).alias("hot")))
    paired = halves.join(met, "half").groupBy("h1").agg(F.max("hot").alias("hot"))
    wanted = cut_lineage(distinct.join(paired, "h1").select(*ROW, "line", "n", "hot"))
    # ranges in order, rows in order within them: the ids rise with the places
    ranged = wanted.repartitionByRange(*ROW, "line").sortWithinPartitions(*ROW, "line")
    return cut_lineage(ranged.withColumn("ord", F.monotonically_increasing_id()))


def _marked(lines: Column) -> Column:
    """A byte string with ``1`` at the places of a sorted array of line numbers and ``0`` before and between."""

    def marks(held: Column) -> Column:
        gap = lambda x, i: x - F.when(i == 0, F.lit(-1)).otherwise(F.element_at(held, F.greatest(i, F.lit(1)))) - 1
        return F.array_join(F.transform(held, lambda x, i: F.concat(F.repeat(F.lit("0"), gap(x, i)), F.lit("1"))), "")

    # a lambda holds the array, so it is made once and not for every element
    return F.encode(F.transform(F.array(lines), marks)[0], "UTF-8")


def _is_marked(mask: Column, i: Column) -> Column:
    return F.coalesce(F.substring(mask, i + 1, F.lit(1)) == F.lit(b"1"), F.lit(False))


def _with_bodies(wanted: DataFrame, docs: DataFrame) -> DataFrame:
    """(ord, n, hot, body): the lines wanted, taken out of each text in one pass over its lines."""
    by_row = wanted.groupBy(*ROW).agg(F.array_sort(F.collect_list(F.struct("line", "ord", "n", "hot"))).alias("w"))  # no more than the lines of one text
    marked = by_row.select(*ROW, "w", _marked(F.col("w.line")).alias("mask"))
    met = marked.join(_rows(docs), ROW)
    bodies = F.filter(F.split("text", "\n"), lambda line, i: _is_marked(F.col("mask"), i))
    each = met.select(F.explode(F.arrays_zip(bodies.alias("body"), F.col("w").alias("w"))).alias("z"))
    return each.select("z.w.ord", "z.w.n", "z.w.hot", "z.body").dropDuplicates(["ord"])


def _emitted(found: DataFrame, tasks: int) -> DataFrame:
    """(key, ord, role, hot): for each line its variants at their position (role 0), its variants anywhere (1) and itself (2)."""
    # dealt before the words are taken apart, so sums along a line move nothing
    single = found.repartition(tasks, "ord").select("ord", "n", "hot", F.posexplode(words_of_line(F.col("body"))).alias("i", "w"))
    values = {f"{name}{seed}": F.xxhash64(F.lit(seed), "w", F.col("i") + shift).bitwiseAND(F.lit(_MASK)) for name, shift in (("own", 0), ("left", -1)) for seed in (1, 2)}
    sums = single.select("ord", "n", "hot", "i", *[v.alias(k) for k, v in values.items()])
    whole = Window.partitionBy("ord")
    along = whole.orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    for seed in (1, 2):
        before = F.sum(f"own{seed}").over(along) - F.col(f"own{seed}")
        after = F.sum(f"left{seed}").over(whole) - F.sum(f"left{seed}").over(along)
        sums = sums.withColumn(f"variant{seed}", before + after).withColumn(f"full{seed}", F.sum(f"own{seed}").over(whole))
    key = lambda role, *parts: F.struct(F.xxhash64(*parts).alias("key"), F.lit(role).alias("role"))
    rows = [key(0, "variant1", "variant2", F.col("n") - 1, "i"), key(1, "variant1", "variant2", F.col("n") - 1)]
    full = key(2, "full1", "full2", F.col("n"))
    each = sums.select("ord", "hot", F.explode(F.when(F.col("i") == 0, F.array(*rows, full)).otherwise(F.array(*rows))).alias("v"))
    return each.select("v.key", "ord", "v.role", "hot")


def _least(emitted: DataFrame) -> DataFrame:
    """The earliest line of each key by role; substitutions meet at role 0, a whole line (2) meets lines with a word more (1)."""
    of = lambda role: F.min(F.when(F.col("role") == role, F.col("ord")))
    return emitted.groupBy("key").agg(of(0).alias("same"), of(1).alias("more"), of(2).alias("whole"), F.count("*").alias("k")).where("k > 1")


def _meeting(emitted: DataFrame, least: DataFrame) -> DataFrame:
    """(ord, first): lines with an earlier one at one of their keys."""
    other = F.when(F.col("role") == 0, F.col("same")).when(F.col("role") == 1, F.col("whole")).otherwise(F.col("more"))
    return emitted.join(least, "key").where(other < F.col("ord")).select("ord", other.alias("first"))


def _packed(emitted: DataFrame) -> DataFrame:
    """Rows dealt by key; line and role share a number meanwhile."""
    dealt = emitted.select("key", (F.col("ord") * 4 + F.col("role")).alias("packed")).repartition("key")
    return dealt.select("key", F.shiftright("packed", 2).alias("ord"), F.col("packed").bitwiseAND(3).alias("role"))


def _near(found: DataFrame, tasks: int, many: int) -> DataFrame:
    """(ord) of the lines (ord, n, hot, body) that have an earlier one within one edit.

    Lines that share a key share a half, so keys of more than ``many`` rows are
    found among the lines of hot halves; their minima are taken before dealing.
    """
    emitted = _emitted(found, tasks)
    if found.where("hot").isEmpty():
        dealt = _packed(emitted)
        met = _meeting(dealt, _least(dealt))
    else:
        hot = cut_lineage(emitted.where("hot").groupBy("key").agg(F.count("*").alias("k")).where(F.col("k") > many).select("key"))
        dealt, crowded = _packed(emitted.join(hot, "key", "left_anti")), emitted.join(hot, "key", "left_semi")
        met = _meeting(dealt, _least(dealt)).union(_meeting(crowded, cut_lineage(_least(crowded))))
    earlier = met.groupBy("ord").agg(F.min("first").alias("first"))
    mine = earlier.join(found.select("ord", "body"), "ord")
    theirs = found.select(F.col("ord").alias("first"), F.col("body").alias("earlier"))
    both = mine.join(theirs, "first").select("ord", words_of_line(F.col("body")).alias("a"), words_of_line(F.col("earlier")).alias("b"))
    return both.where(within_one_edit(F.col("a"), F.col("b"))).select("ord")


def marked_rows(docs: DataFrame, min_words: int = 8, many: int = 1_000_000) -> DataFrame:
    """(doc_id, th, mask, n_kept, n_near): for each row with words which of its lines stay, and how many went for an earlier neighbour."""
    distinct = cut_and_release(_distinct_lines(docs, min_words), rounds=3)
    wanted = _with_shared_half(distinct, many)
    firsts = cut_lineage(distinct.groupBy(*ROW).agg(F.collect_list("line").alias("firsts")))
    del distinct  # so its files go at the next cut
    found = cut_and_release(_with_bodies(wanted, docs), rounds=3)
    session_tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n_words = found.agg(F.sum(F.col("n").cast("long"))).first()[0] or 0
    near = wanted.join(_near(found, max(session_tasks, -(-n_words // _WORDS_A_TASK)), many), "ord").groupBy(*ROW).agg(F.collect_list("line").alias("nears"))
    near = cut_lineage(near)
    del found, wanted
    none = F.array().cast("array<int>")
    kept = firsts.join(near, ROW, "left").select(*ROW, F.array_sort(F.array_except("firsts", F.coalesce("nears", none))).alias("kept"), F.coalesce(F.size("nears"), F.lit(0)).cast("long").alias("n_near"))
    out = kept.select(*ROW, _marked(F.col("kept")).alias("mask"), F.size("kept").cast("long").alias("n_kept"), F.greatest("n_near", F.lit(0)).alias("n_near"))
    release(docs.sparkSession, rounds=3)
    return out


def line_counts(docs: DataFrame, min_words: int = 8, many: int = 1_000_000) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_lines, n_blank, n_kept, n_near, n_exact.

    ``n_kept`` counts lines with words that stay, ``n_near`` those removed for
    an earlier neighbour and ``n_exact`` those removed as copies; lines without
    words always stay.  A null text has no lines; with a null id all lines stay.
    Other columns are ignored; an empty table gives no rows.
    """
    lines, zero = F.split("text", "\n"), F.lit(0).cast("long")
    blank = F.size(F.filter(lines, lambda x: ~x.rlike(WORDED))).cast("long")
    known = F.col("text").isNotNull()
    counted = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), known.alias("known"), F.when(known, F.size(lines).cast("long")).otherwise(zero).alias("n_lines"), F.when(known, blank).otherwise(zero).alias("n_blank"))
    apart = counted.where("doc_id IS NULL OR NOT known").select("doc_id", "n_lines", "n_blank", (F.col("n_lines") - F.col("n_blank")).alias("n_kept"), zero.alias("n_near"))
    marked = marked_rows(docs, min_words, many).select(*ROW, F.col("n_kept").alias("k"), F.col("n_near").alias("r"))
    told = counted.where("doc_id IS NOT NULL AND known").join(marked, ROW, "left").select("doc_id", "n_lines", "n_blank", F.coalesce("k", zero).alias("n_kept"), F.coalesce("r", zero).alias("n_near"))
    return told.union(apart).withColumn("n_exact", F.col("n_lines") - F.col("n_blank") - F.col("n_kept") - F.col("n_near"))


def dedup_lines(docs: DataFrame, min_words: int = 8, many: int = 1_000_000) -> DataFrame:
    """``docs`` (all columns) with the repeated lines taken out of ``text``; no row goes.

    Null texts and rows with a null id stay as they are; a text whose lines all
    repeat earlier ones becomes empty.  An empty table stays empty.
    """
    marked = marked_rows(docs, min_words, many).select(F.col("doc_id").alias("row_id_"), F.col("th").alias("row_th_"), F.col("mask").alias("row_mask_"))
    takes_part = F.col("doc_id").isNotNull() & F.col("text").isNotNull()
    met = docs.where(takes_part).join(marked, (F.col("doc_id").cast("long") == F.col("row_id_")) & (F.xxhash64("text") == F.col("row_th_")), "left")
    stays = F.filter(F.split("text", "\n"), lambda line, i: ~line.rlike(WORDED) | _is_marked(F.col("row_mask_"), i))
    return met.withColumn("text", F.array_join(stays, "\n")).select(*docs.columns).union(docs.where(~takes_part))
