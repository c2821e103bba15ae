"""Mixing sources to target weights: packed blocks, drawn per output shard, joined by index.

DataFrame functions only.

* The words of each source form one stream, cut into blocks of fixed length (the
  last block of a source is shorter).
* Every source gets a number of slots in proportion to its target.  The slots of
  each output shard are drawn independently with those shares, so a shard's
  counts by source are a multinomial draw.
* The draws of all shards miss the totals by little.  That is repaired: a source
  drawn too often gives slots, picked by a pseudorandom permutation of its
  draws, to those drawn too seldom, so totals do not fluctuate.
* A source's slots run through its blocks epoch by epoch, each epoch in the order
  of another pseudorandom permutation of the block numbers, so no block is used
  more than once more often than another.
* Slots and blocks meet in one join on (source, block).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparsegrid.plans.lineage import cut_and_release, cut_lineage

WORD = r"[^\x20\x09-\x0D]+"
_COPIES = 1 << 12  # copies of one row that one task writes out
_SLOTS = 1 << 18  # slots that one task draws
_WALK = 16


def permuted(x: Column, n: Column, key: Column) -> Column:
    """A pseudorandom permutation of 0..n-1, chosen by ``key``, at ``x``.

    The numbers are laid out in a rectangle of about sqrt(n) rows; rounds add a
    hash of one coordinate to the other.  The few results beyond n go round again.
    """
    rows = F.ceil(F.sqrt(n.cast("double")))
    cols = F.floor((n + rows - 1) / rows)

    def once(v: Column) -> Column:
        a, b = F.floor(v / cols), v % cols
        for turn in range(2):
            a = F.pmod(a + F.pmod(F.xxhash64(b, key, F.lit(2 * turn)), rows), rows)
            b = F.pmod(b + F.pmod(F.xxhash64(a, key, F.lit(2 * turn + 1)), cols), cols)
        return a * cols + b

    first = once(x)
    walked = F.aggregate(F.sequence(F.lit(1), F.lit(_WALK)), first, lambda v, _: F.when(v < n, v).otherwise(once(v)))
    return F.when(first < n, first).otherwise(walked)


@dataclass
class Mix:
    """``plan``: a row for each source; ``packed``: a row for each document; ``drawn``: a row for each slot; ``pieces``: what the mix takes."""

    plan: DataFrame
    packed: DataFrame
    drawn: DataFrame
    pieces: DataFrame
    block_words: int


def source_targets(sizes: DataFrame, weights: tuple[int, ...], cap: int) -> DataFrame:
    """Adds weight and target to (source, source_size).

    Sources in code point order, null last, weigh ``weights`` in turn and share
    all words; none gets more than ``cap`` times its own, the excess goes to the
    others by weight: all get the same multiple of their weight or their limit.
    """
    everything = Window.partitionBy()
    ranked = sizes.withColumn("sid", F.row_number().over(Window.orderBy(F.col("source").isNull(), "source")) - 1)
    ranked = ranked.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.col("sid") % len(weights) + 1).cast("int")).cast("long"))
    by_limit = Window.orderBy(F.col("source_size") / F.col("weight"), "sid")
    before = by_limit.rowsBetween(Window.unboundedPreceding, -1)
    ranked = ranked.withColumn("total", F.sum("source_size").over(everything)).withColumn("all_weight", F.sum("weight").over(everything))
    ranked = ranked.withColumn("level", (F.col("total") - cap * F.coalesce(F.sum("source_size").over(before), F.lit(0))).cast("double") / (F.col("all_weight") - F.coalesce(F.sum("weight").over(before), F.lit(0))).cast("double"))
    # the first source, from the tightest limit on, whose share at its level stays within its limit sets the level of all after it
    level = F.min(F.when(F.col("level") * F.col("weight") <= cap * F.col("source_size"), F.struct(F.col("source_size") / F.col("weight"), "sid", "level"))).over(everything)
    ranked = ranked.withColumn("common", level["level"])
    target = F.when(F.col("common").isNull() | (F.col("common") * F.col("weight") > cap * F.col("source_size")), (cap * F.col("source_size")).cast("double")).otherwise(F.col("common") * F.col("weight"))
    return ranked.select("sid", "source", "source_size", "weight", target.alias("target"))


def _mark() -> Column:
    """What a row is known by when its words are fetched: a hash of id and text."""
    return F.xxhash64(F.col("doc_id").cast("long"), F.col("text")).alias("mark")


def mix_sources(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3, block_words: int = 64, shard_slots: int = 2048, seed: int = 17, chunk_rows: int = 512) -> Mix:
    """Mixes the rows of ``docs`` (doc_id, text, source).

    ``pieces``: shard, slot, sid, block, at (words of the block before the
    piece), doc_id, mark, off, first_word, n_words; ordered by (shard, slot, at) they
    are the mixed corpus.  Null and empty texts take no part; a null source is a
    source of its own; rows with a null or repeated id are rows like others (off,
    the place in the source's stream, tells them apart); an empty table gives
    empty tables; other columns are ignored.  Every run gives the same mix.
    """
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"), _mark())
    sized = cut_lineage(sized.groupBy("source", "doc_id", "mark", "size").agg(F.count("*").alias("copies")))
    sums = sized.groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("source_size"), F.count("*").alias("rows"))
    plan = source_targets(sums.select("source", "source_size"), weights, cap)
    blocks = F.ceil(F.col("source_size") / block_words)
    slots = F.when(F.col("source_size") > 0, F.least(F.round(F.col("target") * blocks / F.col("source_size")).cast("long"), cap * blocks)).otherwise(0)
    plan = plan.withColumn("blocks", blocks).withColumn("slots", slots)
    plan = cut_lineage(plan.withColumn("start", F.sum("slots").over(Window.orderBy("sid")) - F.col("slots")).join(sums.select(F.col("source").alias("s"), "rows"), F.col("source").eqNullSafe(F.col("s"))).drop("s"))

    packed = cut_and_release(_streams(sized, plan, seed, chunk_rows), rounds=3)
    at = _pieces_of(block_words)
    cut = packed.where("size > 0").select("sid", "doc_id", "mark", "off", F.explode(at).alias("p")).select("sid", "p.block", "doc_id", "mark", "off", "p.at", "p.first_word", "p.n_words")

    dealt = draw_slots(plan, shard_slots, seed).join(plan.select("sid", "blocks"), "sid")
    epoch = F.floor(F.col("q") / F.col("blocks"))
    drawn = dealt.select("shard", "slot", "sid", permuted(F.col("q") % F.col("blocks"), F.col("blocks"), F.xxhash64(F.lit(seed), "sid", epoch)).alias("block"))
    # the slots are many, though their plan is small
    return Mix(plan.drop("rows"), packed, drawn, drawn.hint("merge").join(cut, ["sid", "block"]), block_words)


def _pieces_of(block_words: int) -> Column:
    """What of a row at ``off`` with ``size`` words lies in which block: (block, at, first_word, n_words) in order."""
    begin, end = F.col("off"), F.col("off") + F.col("size")

    def piece(block: Column) -> Column:
        lo, hi = F.greatest(block * block_words, begin), F.least((block + 1) * block_words, end)
        return F.struct(block.alias("block"), (lo - block * block_words).alias("at"), (lo - begin).alias("first_word"), (hi - lo).alias("n_words"))

    return F.transform(F.sequence(F.floor(begin / block_words), F.floor((end - 1) / block_words)), piece)


def _streams(sized: DataFrame, plan: DataFrame, seed: int, chunk_rows: int) -> DataFrame:
    """The rows of each source one after the other in a seeded order: off is where a row begins.

    A source's rows are dealt to chunks of about ``chunk_rows``; a row that is
    there many times is one row until its place is known.
    """
    of = plan.select("sid", F.col("source").alias("s"), "source_size", "target", "rows")
    chunked = sized.join(of, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    chunked = chunked.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "mark", F.lit(seed)), F.ceil(F.col("rows") / chunk_rows))).withColumn("words", F.col("size") * F.col("copies"))
    base = chunked.groupBy("sid", "chunk").agg(F.sum("words").alias("all_words"))
    base = base.withColumn("base", F.sum("all_words").over(Window.partitionBy("sid").orderBy("chunk")) - F.col("all_words")).drop("all_words")
    within = Window.partitionBy("sid", "chunk").orderBy(F.xxhash64("doc_id", F.lit(seed + 1)), "doc_id", "mark").rowsBetween(Window.unboundedPreceding, 0)
    placed = chunked.withColumn("run", F.sum("words").over(within)).join(base, ["sid", "chunk"])
    first = F.col("base") + F.col("run") - F.col("words")
    columns = ["doc_id", "mark", "source", "sid", "size", "source_size", "target"]
    one = placed.where("copies = 1").select(*columns, first.alias("off"))
    more = placed.where("copies > 1").select(*columns, first.alias("first"), "copies", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("copies") - 1) / _COPIES))).alias("part"))
    spread = more.repartition("sid", "first", "part").select(*columns, "first", F.explode(F.sequence(F.col("part") * _COPIES, F.least((F.col("part") + 1) * _COPIES, F.col("copies")) - 1)).alias("copy"))
    return one.union(spread.select(*columns, (F.col("first") + F.col("copy") * F.col("size")).alias("off")))


def draw_slots(plan: DataFrame, shard_slots: int, seed: int) -> DataFrame:
    """(shard, slot, sid, q): a source for every slot, and its number q among the source's slots, from 0.

    Slots draw a number below the sum of all slots; the source whose range holds
    it is found by a join on cells of equal length.  Ranks of draws within a
    source come from counts by shard.
    """
    spark = plan.sparkSession
    total = int(plan.agg(F.sum("slots")).first()[0] or 0)
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-total // _SLOTS))
    cell = max(1, total // 4096)
    ranges = plan.where("slots > 0").select("sid", "slots", "start", F.explode(F.sequence(F.floor(F.col("start") / cell), F.floor((F.col("start") + F.col("slots") - 1) / cell))).alias("cell"))
    shard = F.floor(F.col("x") / shard_slots).alias("shard")
    x = spark.range(0, total, 1, tasks).select(F.col("id").alias("x"), F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(total or 1)).alias("u"))
    drawn = x.withColumn("cell", F.floor(F.col("u") / cell)).join(ranges, "cell").where("u >= start and u < start + slots").select("x", "sid")
    drawn = cut_and_release(drawn).select("x", "sid", shard)
    by_shard = drawn.groupBy("shard", "sid").agg(F.count("*").alias("c"))
    upto = by_shard.withColumn("before", F.sum("c").over(Window.partitionBy("sid").orderBy("shard")) - F.col("c")).drop("c")
    rank = F.row_number().over(Window.partitionBy("shard", "sid").orderBy("x")) - 1
    ranked = drawn.withColumn("rank", rank).join(upto, ["shard", "sid"]).select("x", "sid", (F.col("before") + F.col("rank")).alias("r"))

    counts = plan.where("slots > 0").select("sid", "slots").join(drawn.groupBy("sid").agg(F.count("*").alias("d")), "sid", "left").select("sid", "slots", F.coalesce("d", F.lit(0)).alias("d"))
    over, under = F.greatest(F.col("d") - F.col("slots"), F.lit(0)), F.greatest(F.col("slots") - F.col("d"), F.lit(0))
    running = lambda c: F.sum(c).over(Window.orderBy("sid")) - c
    counts = cut_lineage(counts.select("sid", "slots", "d", running(over).alias("gives"), running(under).alias("takes")))
    q = permuted(F.col("r"), F.col("d"), F.xxhash64(F.lit(seed + 2), "sid"))
    numbered = ranked.join(counts.select("sid", "slots", "d", "gives"), "sid").select("x", "sid", "slots", "gives", q.alias("q"))
    # m numbers the slots that are given away
    numbered = cut_and_release(numbered.select("x", "sid", "q", F.when(F.col("q") >= F.col("slots"), F.col("gives") + F.col("q") - F.col("slots")).alias("m")), rounds=3)
    missing = counts.where("slots > d").select(F.col("sid").alias("to"), "d", "takes", F.explode(F.sequence(F.lit(0).cast("long"), F.col("slots") - F.col("d") - 1)).alias("k"))
    missing = missing.select((F.col("takes") + F.col("k")).alias("m"), "to", (F.col("d") + F.col("k")).alias("as"))
    moved = numbered.where("m IS NOT NULL").select("x", "m").join(missing, "m").select("x", F.col("to").alias("sid"), F.col("as").alias("q"))
    return numbered.where("m IS NULL").select("x", "sid", "q").union(moved).select(shard, (F.col("x") % shard_slots).alias("slot"), "sid", "q")


def taken_words(mix: Mix) -> DataFrame:
    """``packed`` with ``taken``: how many words of each document the mix takes, repeats counted."""
    taken = mix.pieces.groupBy("sid", "off").agg(F.sum("n_words").alias("taken"))
    used = mix.packed.where("size > 0").join(taken, ["sid", "off"], "left")
    columns = ["doc_id", "source", "size", "source_size", "target"]
    return used.select(*columns, F.coalesce("taken", F.lit(0)).cast("long").alias("taken")).union(mix.packed.where("size = 0").select(*columns, F.lit(0).cast("long").alias("taken")))


def mixed_corpus(docs: DataFrame, mix: Mix) -> DataFrame:
    """The pieces of the mix with their words, in whole shards; repeated rows are taken as often as the mix takes them.

    Each text is cut into the pieces of its blocks where its place is told, once;
    pieces, not texts, then meet the slots.
    """
    texts = docs.where(F.col("text").isNotNull()).select(F.col("doc_id").cast("long").alias("id_"), _mark(), "text").dropDuplicates(["id_", "mark"])
    placed = mix.packed.where("size > 0").select("doc_id", F.col("mark").alias("mark_"), "sid", "off", "size")
    met = placed.join(texts, F.col("doc_id").eqNullSafe(F.col("id_")) & (F.col("mark_") == F.col("mark")))

    def pieces(words: Column) -> Column:
        text = lambda p: F.array_join(F.slice(words, (p["first_word"] + 1).cast("int"), p["n_words"].cast("int")), " ")
        return F.transform(_pieces_of(mix.block_words), lambda p: F.struct(p["block"].alias("block"), p["at"].alias("at"), p["first_word"].alias("first_word"), p["n_words"].alias("n_words"), text(p).alias("text")))

    # a lambda holds the words, so a text is taken apart once and not for every piece
    made = F.transform(F.array(F.regexp_extract_all("text", F.lit(WORD), F.lit(0))), pieces)[0]
    cut = met.select("sid", "doc_id", F.explode(made).alias("p")).select("sid", "doc_id", "p.*")
    return mix.drawn.hint("merge").join(cut, ["sid", "block"]).select("shard", "slot", "at", "doc_id", "first_word", "n_words", "text")
