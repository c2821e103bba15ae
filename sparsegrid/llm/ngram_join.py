"""N-gram Jaccard join by grouped prefixes.

Steps, each one distributed:

1. every text becomes the set of its distinct word n-grams (64-bit hashes);
   equal sets form a class, named by its smallest doc_id;
2. a count sketch of fixed size over the n-grams of all texts gives the order
   "rare first": (level of the sketched count, hash).  Any total order keeps the
   prefix filter exact; this one keeps frequent n-grams out of the prefixes;
3. classes with the same prefix and the same size form a group, led by its
   smallest doc_id; groups meet on the n-grams of their prefixes;
4. first round: the leads of groups that meet in buckets of at most ``small``
   groups and pass the size and position filters; in larger buckets stars (every
   group against one pivot of each of its buckets); in every group its members
   against its lead.  Verified links are contracted to components;
5. second round: of the groups that meet, and of the members of groups, those
   that still lie in different components and pass the filters are expanded to
   their members and verified; what is found joins the components.

Verification is exact on whole sets.  ``ngram_components`` returns components
and class membership, without listing the pairs within one component;
``ngram_links`` returns all links between classes, and ``link_counts`` how many a
row has.

Joins are sort-merge joins: nothing that grows with the input is broadcast, but
for the ids of at most ``few`` pairs, which are counted first.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sparsegrid.llm.graph import EDGES, components_of, forest_of, local_forest
from sparsegrid.llm.textkernel import SPACED, mix64, words_of
from sparsegrid.plans.lineage import cut_and_release

SKETCH_BITS = 22
_BLOCK_BITS = 17
_FAN = 1024  # sketches of tasks are summed in that many groups first
_ODD = np.array([0x8F3A1234567B1D4D, 0x1234567FEDCBA987, 0xC7777ABC12398711, 0x3456789ABCDEF12B], dtype=np.uint64)
_STEP = np.uint64(0x9FB21C651E98DF25)


def shingle_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the n-grams of one word sequence; shorter ones count whole."""
    k = min(n, len(words))
    if k == 0:
        return np.zeros(0, np.uint64)
    out = np.full(len(words) - k + 1, np.uint64(k))
    for j in range(k):
        out = (out + words[j : len(words) - k + 1 + j] * _ODD[j % 4]) * _STEP
    return mix64(out)


def shingle_sets(column: pa.Array, n: int) -> Iterator[np.ndarray]:
    """The sorted set of n-gram hashes of every text of an Arrow column."""
    for _, bounds, words in words_of(column, SPACED):
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            yield np.unique(shingle_hashes(words[a:b], n))


def prefix_length(size: int, num: int, den: int) -> int:
    """How many of the first elements must hold one in common with any partner."""
    return size - -(-size * num // den) + 1 if size else 0


def _sketch_parts(n: int):
    def run(batches):
        counts = np.zeros(1 << SKETCH_BITS, np.uint32)
        for batch in batches:
            for s in shingle_sets(batch.column(0), n):
                np.add.at(counts, (s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), np.uint32(1))
        blocks = counts.reshape(-1, 1 << _BLOCK_BITS)
        task = TaskContext.get().partitionId() % _FAN
        yield _sketch_rows({(k, task): b for k, b in enumerate(blocks)})

    return run


def _sketch_rows(blocks: dict[tuple[int, int], np.ndarray]) -> pa.RecordBatch:
    packed = [zlib.compress(b.astype("<u8").tobytes(), 1) for b in blocks.values()]
    return pa.RecordBatch.from_arrays([pa.array([k for k, _ in blocks], pa.int32()), pa.array([t for _, t in blocks], pa.int32()), pa.array(packed, pa.binary())], ["block", "task", "counts"])


def _sketch_sums(batches):
    """The counts of each block summed by group of tasks."""
    yield _sketch_rows(_summed(batches))


def _sketch_levels(batches):
    """The levels of each block, from the sums of all groups of tasks."""
    total = _summed(batches)
    yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in total], pa.int32()), pa.array([_levels(b).tobytes() for b in total.values()], pa.binary())], ["block", "levels"])


def _summed(batches) -> dict[tuple[int, int], np.ndarray]:
    total: dict[tuple[int, int], np.ndarray] = {}
    for batch in batches:
        for block, task, counts in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
            part = np.frombuffer(zlib.decompress(counts.as_py()), "<u8")
            total[block, task] = total[block, task] + part if (block, task) in total else part
    return total


def _levels(counts: np.ndarray) -> np.ndarray:
    return np.floor(4 * np.log2(np.maximum(counts, 1))).astype(np.uint8)


def frequency_levels(texts: DataFrame, n: int) -> np.ndarray:
    """For each bucket of n-gram hashes, the quarter-octave of its count over all texts.

    2**SKETCH_BITS bytes whatever the input: the only thing that the driver
    gathers and broadcasts.  The tasks' sketches are summed in two steps, so no
    reducer reads more than a share of them.
    """
    shape = "block int, task int, counts binary"
    parts = texts.mapInArrow(_sketch_parts(n), shape).repartition("block", "task").mapInArrow(_sketch_sums, shape)
    levels = parts.select("block", F.lit(0).alias("task"), "counts").repartition("block").mapInArrow(_sketch_levels, "block int, levels binary")
    out = np.zeros(1 << SKETCH_BITS, np.uint8)
    for row in levels.collect():
        out[row.block << _BLOCK_BITS : (row.block + 1) << _BLOCK_BITS] = np.frombuffer(row.levels, np.uint8)
    return out


def class_key(s: np.ndarray) -> int:
    """A 64-bit name of a set."""
    return int(mix64(mix64(s).sum(dtype=np.uint64, keepdims=True) + np.uint64(len(s)))[0].astype(np.int64))


def _signatures(levels, n: int, num: int, den: int):
    """Per text: set size, class key, group key and prefix."""

    def run(batches):
        rank = levels.value.astype(np.uint64) << np.uint64(56)
        low = np.uint64((1 << 56) - 1)
        for batch in batches:
            size, cls, grp, prefix = [], [], [], []
            for s in shingle_sets(batch.column(1), n):
                keys = rank[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)] | (s & low)
                p = prefix_length(len(s), num, den)
                keys = np.sort(np.partition(keys, p - 1)[:p]) if p else keys
                size.append(len(s))
                cls.append(class_key(s))
                grp.append(int(mix64(mix64(keys).sum(dtype=np.uint64, keepdims=True) ^ np.uint64(len(s)))[0].astype(np.int64)))
                prefix.append(keys.astype(np.int64))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(size, pa.int64()), pa.array(cls, pa.int64()), pa.array(grp, pa.int64()), pa.array(prefix, pa.list_(pa.int64()))],
                ["doc_id", "size", "cls", "grp", "prefix"],
            )

    return run


def _verified(n: int, num: int, den: int, forest: bool):
    """Streams blocks of (left texts, then their partners) and gives the true links, or only their forest.

    An id may stand for several texts; they count as one document.
    """

    def run(batches):
        left, known, left_id = [], set(), None
        ends = [], []
        told = lambda: (np.array(e, np.int64) for e in ends)
        for batch in batches:
            a, b, x, y = (batch.column(c).to_pylist() for c in ("a", "b", "na", "nb"))
            for i, s in enumerate(shingle_sets(batch.column("text"), n)):
                if b[i] is None:
                    if left_id != a[i]:
                        left, known, left_id = [], set(), a[i]
                    if (key := class_key(s)) not in known:
                        known.add(key)
                        left.append(s)
                elif left_id == a[i] and any(_similar(t, s, num, den) for t in left):
                    ends[0].append(x[i])
                    ends[1].append(y[i])
            if not forest:
                yield pa.RecordBatch.from_arrays([pa.array(e) for e in told()], ["child", "parent"])
                ends = [], []
        if forest:
            yield forest_of(*told())

    return run


def _similar(s: np.ndarray, t: np.ndarray, num: int, den: int) -> bool:
    if not len(s) or not len(t):
        return False
    at = np.searchsorted(s, t)
    at[at == len(s)] = 0
    common = int(np.count_nonzero(s[at] == t))
    return den * common >= num * (len(s) + len(t) - common)


def _verify(pairs: DataFrame, docs: DataFrame, n: int, num: int, den: int, few: int, forest: bool = True, per_task: int = 256) -> DataFrame:
    """The forest (child, parent) of the links among pairs (a, b, na, nb), given with their lineage cut, or all these links.

    a and b are documents, na and nb the vertices that stand for them.  Left
    texts with many partners are sent to several tasks.  While the pairs are few
    (counted here) their ids go to the texts, else the texts are dealt.
    """
    n_pairs = pairs.count()
    # a table of its own, so the join below deals a text with very many partners to several tasks
    tasks = cut_and_release(pairs.groupBy("a").agg(F.ceil(F.count("*") / per_task).alias("tasks")))
    salted = pairs.join(tasks.hint("merge"), "a").select("a", F.pmod(F.xxhash64("b"), F.col("tasks")).alias("salt"), "b", "na", "nb", F.col("b").alias("doc"))
    none = F.lit(None).cast("long")
    lefts = tasks.select("a", F.explode(F.sequence(F.lit(0).cast("long"), F.col("tasks") - 1)).alias("salt")).select("a", "salt", none.alias("b"), none.alias("na"), none.alias("nb"), F.col("a").alias("doc"))
    need = salted.union(lefts)
    text = docs.select(F.col("doc_id").alias("doc"), "text")
    if n_pairs <= few:
        ids = pairs.select(F.explode(F.array("a", "b")).alias("doc")).distinct()
        text = text.join(F.broadcast(ids), "doc")  # 2 * few ids at most
    rows = need.join(text.hint("merge"), "doc").select("a", "salt", "b", "na", "nb", "text")
    dealt = rows.repartition("a", "salt").sortWithinPartitions("a", "salt", F.col("b").asc_nulls_first())
    return dealt.mapInArrow(_verified(n, num, den, forest), EDGES)


def ngram_components(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, small: int = 32, few: int = 200_000) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): doc_id, size, component.

    ``size`` is the number of distinct word n-grams (whole sequence where there
    are fewer than ``n`` words, none without words or text) and ``component``
    the smallest doc_id that links reach; two texts link where
    ``den * |intersection| >= num * |union|``.  Other columns of ``docs`` are
    ignored.  Rows with a null doc_id get their size and no component and link
    with nothing; repeated rows come back as often as they are there; rows that
    share an id are one document, reached through the links of each of its texts
    with words; an empty table gives no rows.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    sign, worded, classes, multi = _signed(docs, n, num, den)
    postings = cut_and_release(_postings(worded, small))
    large = postings.where("large").drop("large")
    some_multi, some_large = not multi.isEmpty(), not large.isEmpty()

    near = cut_and_release(_meeting_in_small(postings.where("not large"), num, den))
    tried = near.select("a", "b").union(multi.select(F.col("lead").alias("a"), F.col("doc").alias("b")))
    if some_large:
        tried = tried.union(_stars(large, num, den))
    tried = cut_and_release(tried.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    same = _one_id_several_texts(worded, classes)
    found = _verify(tried.select("*", F.col("a").alias("na"), F.col("b").alias("nb")), docs, n, num, den, few)
    labels = components_of(found if same is None else found.union(same))

    rest = _apart(large if some_large else None, near, multi if some_multi else None, labels, num, den)
    placed = _labelled(classes.select("cls", "doc"), "doc", labels, "label")
    if rest is not None:
        rest = cut_and_release(rest.join(tried.hint("merge"), ["a", "b"], "left_anti"))
        if not rest.isEmpty():
            more = components_of(_verify(rest, docs, n, num, den, few))
            placed = _labelled(placed, "label", more, "label")
    member = placed.select("cls", F.col("label").alias("component"))
    has = (F.col("size") > 0) & F.col("doc_id").isNotNull()
    return sign.select("doc_id", "size", "cls").join(member.hint("merge"), "cls", "left").select("doc_id", "size", F.when(has, F.col("component")).otherwise(F.col("doc_id")).alias("component"))


def _signed(docs: DataFrame, n: int, num: int, den: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Signatures of all rows, those with words and id, their classes, and the members of groups with several."""
    levels = docs.sparkSession.sparkContext.broadcast(frequency_levels(docs.select("text"), n))
    sign = cut_and_release(docs.mapInArrow(_signatures(levels, n, num, den), "doc_id long, size long, cls long, grp long, prefix array<long>"))
    worded = sign.where("size > 0 and doc_id is not null")
    classes = cut_and_release(worded.groupBy("grp", "size", "cls").agg(F.min("doc_id").alias("doc")))
    several = classes.groupBy("grp", "size").agg(F.min("doc").alias("lead"), F.count("*").alias("members")).where("members > 1").drop("members")
    multi = cut_and_release(classes.join(several.hint("merge"), ["grp", "size"]).select("grp", "size", "doc", "lead"))
    return sign, worded, classes, multi


def ngram_links(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, few: int = 200_000) -> tuple[DataFrame, DataFrame]:
    """(links, members): all links between different texts, and the rows of each class of equal sets.

    ``links`` (a, b), a < b, are pairs of classes, each named by its smallest
    doc_id; ``members`` (doc_id, class_id) has a row for each row of ``docs`` with
    words and id, so copies are not expanded into pairs.  No link is left out:
    every pair of groups that meet on an n-gram of their prefixes and pass the
    size and position filters is expanded and verified.  A group of k near copies
    has k * k / 2 links, and so many are made: where only components are asked
    for, ``ngram_components`` does without them.  Rows that share an id are one
    document; other columns are ignored; an empty table has no links.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    _, worded, classes, multi = _signed(docs, n, num, den)
    postings = cut_and_release(_postings(worded, 1 << 62).drop("large"))
    meeting = cut_and_release(_meeting_in_small(postings, num, den))
    of = lambda g, s, d: multi.select(F.col("grp").alias(g), F.col("size").alias(s), F.col("doc").alias(d)).hint("merge")
    both = meeting.join(of("ga", "sa", "da"), ["ga", "sa"], "left").join(of("gb", "sb", "db"), ["gb", "sb"], "left").select(F.coalesce("da", "a").alias("a"), F.coalesce("db", "b").alias("b"))
    own = multi.alias("x").join(multi.alias("y").hint("merge"), ["grp", "size"]).where("x.doc < y.doc").select(F.col("x.doc").alias("a"), F.col("y.doc").alias("b"))
    pairs = both.union(own).where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    pairs = cut_and_release(pairs.select("a", "b", F.col("a").alias("na"), F.col("b").alias("nb")))
    links = cut_and_release(_verify(pairs, docs, n, num, den, few, forest=False).distinct())
    members = worded.select("doc_id", "cls").join(classes.select("cls", F.col("doc").alias("class_id")).hint("merge"), "cls").select("doc_id", "class_id")
    return links.select(F.col("child").alias("a"), F.col("parent").alias("b")), members


def link_counts(links: DataFrame, members: DataFrame) -> DataFrame:
    """(doc_id, class_id, n_links): how many other rows each row is linked with, copies counted."""
    sizes = members.groupBy("class_id").agg(F.count("*").alias("n"))
    ends = links.select(F.col("a").alias("class_id"), F.col("b").alias("other")).union(links.select(F.col("b").alias("class_id"), F.col("a").alias("other")))
    near = ends.join(sizes.select(F.col("class_id").alias("other"), "n").hint("merge"), "other").groupBy("class_id").agg(F.sum("n").alias("k"))
    of = sizes.join(near.hint("merge"), "class_id", "left").select("class_id", (F.col("n") - 1 + F.coalesce("k", F.lit(0))).alias("n_links"))
    return members.join(of.hint("merge"), "class_id").select("doc_id", "class_id", "n_links")


def _one_id_several_texts(worded: DataFrame, classes: DataFrame) -> DataFrame | None:
    """Edges that make the classes of one id one vertex; None where no id has several."""
    twice = cut_and_release(worded.groupBy("doc_id").agg(F.min("cls").alias("lo"), F.max("cls").alias("hi")).where("lo <> hi").select("doc_id"))
    if twice.isEmpty():
        return None
    own = worded.select("doc_id", "cls").join(twice.hint("merge"), "doc_id", "left_semi").join(classes.select("cls", "doc").hint("merge"), "cls")
    return own.where("doc_id <> doc").select(F.col("doc_id").alias("a"), F.col("doc").alias("b")).mapInArrow(local_forest, EDGES)


def _postings(worded: DataFrame, small: int) -> DataFrame:
    """(key, grp, size, lead, pos, large, lost, big): the n-grams of prefixes that several groups have there.

    Of a prefix's n-grams before one that is shared those that no other group has
    there cannot be common (``lost`` of them); ``big`` counts those before it in
    large buckets.
    """
    groups = cut_and_release(worded.groupBy("grp", "size").agg(F.min("doc_id").alias("lead"), F.first("prefix").alias("prefix")))
    single = groups.select("grp", "size", "lead", F.posexplode("prefix").alias("pos", "key"))
    shared = groups.select(F.explode("prefix").alias("key")).groupBy("key").agg(F.count("*").alias("k")).where("k > 1")
    met = single.join(shared.hint("merge"), "key").select("key", "grp", "size", "lead", "pos", (F.col("k") > small).alias("large"))
    before = Window.partitionBy("grp", "size").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return met.withColumn("lost", F.col("pos") - F.count("key").over(before)).withColumn("big", F.coalesce(F.sum(F.col("large").cast("int")).over(before), F.lit(0)))


def _meeting_in_small(postings: DataFrame, num: int, den: int) -> DataFrame:
    """(ga, sa, a, gb, sb, b): all pairs of groups, with their leads, that meet in a small bucket and can be linked.

    Up to the last n-gram they share there, only the shared ones and those in
    large buckets can be common.
    """
    met = postings.alias("x").join(postings.alias("y").hint("merge"), "key").where("x.grp < y.grp or (x.grp = y.grp and x.size < y.size)").where(_sizes_fit(num, den))
    names = [F.col("x.grp").alias("ga"), F.col("x.size").alias("sa"), F.col("x.lead").alias("a"), F.col("y.grp").alias("gb"), F.col("y.size").alias("sb"), F.col("y.lead").alias("b")]
    pairs = met.groupBy(*names).agg(F.count("*").alias("k"), F.max("x.pos").alias("xp"), F.max("y.pos").alias("yp"), F.max("x.big").alias("xb"), F.max("y.big").alias("yb"))
    most = F.col("k") + F.least("xb", "yb") + F.least(F.col("sa") - F.col("xp") - 1, F.col("sb") - F.col("yp") - 1)
    return pairs.where(most >= _needed(F.col("sa"), F.col("sb"), num, den)).select("ga", "sa", "a", "gb", "sb", "b")


def _labelled(rows: DataFrame, vertex: str, labels: DataFrame, name: str) -> DataFrame:
    """``rows`` with ``name``: the label of the column ``vertex``, or the vertex itself where it has none."""
    told = labels.select(F.col("vertex").alias("vertex_"), F.col("label").alias("label_")).hint("merge")
    out = rows.join(told, rows[vertex] == F.col("vertex_"), "left").withColumn("named_", F.coalesce("label_", vertex))
    return out.select(*[c for c in rows.columns if c != name], F.col("named_").alias(name))


def _band(num: int, den: int):
    """Sizes that can link lie in the same band or in two that touch."""
    return F.floor(F.log(F.col("size").cast("double")) / float(np.log(den / num)))


def _needed(x, y, num: int, den: int):
    """How many n-grams sets of these sizes must have in common."""
    return F.ceil(F.lit(num) * (x + y) / F.lit(float(num + den)) - F.lit(1e-9))


def _sizes_fit(num: int, den: int):
    return (F.col("x.size") * den >= F.col("y.size") * num) & (F.col("y.size") * den >= F.col("x.size") * num)


def _fits(num: int, den: int):
    """Whether two postings (x, y) of the same n-gram can be the first that a linked pair shares.

    Then nothing before them is common, so what comes from there on must be enough
    in both.
    """
    most = F.least(F.col("x.size") - F.col("x.pos"), F.col("y.size") - F.col("y.pos"))
    return _sizes_fit(num, den) & (most >= _needed(F.col("x.size"), F.col("y.size"), num, den))


def _stars(postings: DataFrame, num: int, den: int) -> DataFrame:
    """(a, b): for every group the two pivots that it shares most n-grams with, one pivot for each bucket and size band."""
    banded = postings.withColumn("band", _band(num, den))
    pivots = banded.groupBy("key", "band").agg(F.min(F.struct("lost", "lead", "size", "pos")).alias("p"))
    pivots = pivots.select("key", F.explode(F.array("band", F.col("band") - 1)).alias("band"), "p.lead", "p.size", "p.pos")
    met = pivots.alias("x").join(banded.alias("y").hint("merge"), ["key", "band"]).where("x.lead <> y.lead").where(_fits(num, den))
    counted = met.groupBy(F.col("x.lead").alias("a"), F.col("y.lead").alias("b")).agg(F.count("*").alias("k"))
    # a group has at most two pivots for each n-gram of its prefix
    best = counted.groupBy("b").agg(F.slice(F.sort_array(F.collect_list(F.struct("k", "a")), False), 1, 2).alias("best"))
    return best.select(F.explode("best.a").alias("a"), "b")


def _apart(large: DataFrame | None, near: DataFrame, multi: DataFrame | None, labels: DataFrame, num: int, den: int) -> DataFrame | None:
    """(a, b, na, nb): pairs of documents that meet, can be linked and lie in different components na and nb.

    Leads of groups that meet in large buckets; and where groups have several
    members those of groups that meet anywhere, and those of one group.
    """
    out, meeting = [], near
    held = _labelled(multi, "doc", labels, "label") if multi is not None else None
    if large is not None:
        split = held.groupBy("grp", "size").agg((F.min("label") != F.max("label")).alias("split")).where("split") if held is not None else None
        pairs = _meeting_in_large(_labelled(large, "lead", labels, "comp"), split, num, den)
        if held is not None:
            pairs = cut_and_release(pairs)
            meeting = near.union(pairs.select("ga", "sa", "a", "gb", "sb", "b"))
        out.append(pairs.where("na <> nb").select("a", "b", "na", "nb"))
    if held is not None:
        held = cut_and_release(held.select("grp", "size", "doc", "label"))
        of = lambda g, s, d: held.select(F.col("grp").alias(g), F.col("size").alias(s), F.col("doc").alias(d)).hint("merge")
        both = meeting.join(of("ga", "sa", "da"), ["ga", "sa"], "left").join(of("gb", "sb", "db"), ["gb", "sb"], "left").where("da is not null or db is not null")
        both = both.select(F.coalesce("da", "a").alias("a"), F.coalesce("db", "b").alias("b"))
        out.append(_labelled(_labelled(both, "a", labels, "na"), "b", labels, "nb").where("na <> nb").select("a", "b", "na", "nb"))
        own = held.alias("x").join(held.alias("y").hint("merge"), ["grp", "size"]).where("x.label < y.label")
        out.append(own.select(F.col("x.doc").alias("a"), F.col("y.doc").alias("b"), F.col("x.label").alias("na"), F.col("y.label").alias("nb")))
    if not out:
        return None
    rest = out[0]
    for o in out[1:]:
        rest = rest.union(o)
    turned = F.col("a") > F.col("b")
    ordered = rest.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.when(turned, F.col("nb")).otherwise(F.col("na")).alias("na"), F.when(turned, F.col("na")).otherwise(F.col("nb")).alias("nb"))
    return ordered.distinct()


def _meeting_in_large(postings: DataFrame, split: DataFrame | None, num: int, den: int) -> DataFrame:
    """(ga, sa, a, na, gb, sb, b, nb): groups that meet in a large bucket, can be linked and lie in different components.

    ``split`` names the groups whose members lie in several components.  Within a
    bucket only groups outside its largest component look for partners, so a
    bucket that is one component but for a few groups costs a few rows a member;
    a bucket that is one component costs nothing.
    """
    marked = postings.withColumn("split", F.lit(False)) if split is None else postings.join(split.hint("merge"), ["grp", "size"], "left").withColumn("split", F.coalesce("split", F.lit(False)))
    marked = cut_and_release(marked.select("key", "grp", "size", "lead", "pos", "comp", "split"))
    sizes = marked.groupBy("key", "comp").agg(F.count("*").alias("k"), F.max("split").alias("split"))
    open_ = sizes.groupBy("key").agg(F.max(F.struct("k", "comp")).alias("m"), F.count("*").alias("comps"), F.max("split").alias("any")).where("comps > 1 or any").select("key", F.col("m.comp").alias("main"))
    marked = cut_and_release(marked.join(open_.hint("merge"), "key"))
    met = marked.where("comp <> main or split").alias("x").join(marked.alias("y").hint("merge"), "key").where("(x.grp <> y.grp or x.size <> y.size) and (x.comp <> y.comp or x.split or y.split)").where(_fits(num, den))
    return met.select(F.col("x.grp").alias("ga"), F.col("x.size").alias("sa"), F.col("x.lead").alias("a"), F.col("x.comp").alias("na"), F.col("y.grp").alias("gb"), F.col("y.size").alias("sb"), F.col("y.lead").alias("b"), F.col("y.comp").alias("nb")).distinct()
