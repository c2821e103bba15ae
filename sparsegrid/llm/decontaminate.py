"""Benchmark decontamination with training suffix arrays.

The documents of a batch form a shard.  A shard's word sequence is indexed by
the suffixes that can begin a match (their first words occur in that order in
the benchmark), sorted by their first ``window`` words: the order a window
search needs.  Every distinct window of the test items, that is the beginning of
some test suffix, is binary-searched in each shard; the hits are extended to
longest verbatim matches with their locations.  Items with the same words are
searched once, and a window that many items hold is one hit with a list of items.

Test items travel to the shards in blocks of bounded size.  One block needs one
pass over the texts; of more each has a pass of its own and is taken from the
executors before the next is made, so a benchmark of any size is searched in
full.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.llm.textkernel import ALNUM, words_of
from sparsegrid.plans.lineage import cut_lineage

WINDOW = 13
_GUARD = 0xFFFFFFFF  # a word that no test item has, and the end of a document


@dataclass
class TestBlock:
    """Distinct test sequences over a vocabulary of word hashes, and their distinct windows as search keys."""

    vocabulary: np.ndarray  # sorted word hashes
    items: list[np.ndarray]  # sorted ids of the items of each sequence
    sequences: list[np.ndarray]  # positions in the vocabulary, from 1
    window: int
    lead: int = 1
    leads: np.ndarray | None = None

    def __post_init__(self) -> None:
        """``keys`` holds each distinct window once, ``owner`` and ``start`` where it is first, ``of_key`` all sequences that hold it."""
        wide = f"S{4 * self.window}"
        keys, owner, start = [np.zeros(0, wide)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for k, seq in enumerate(self.sequences):
            w = min(self.window, len(seq))
            table = np.zeros((len(seq) - w + 1, self.window), np.int64)
            table[:, :w] = np.lib.stride_tricks.sliding_window_view(seq, w)
            keys.append(_packed(table, self.window))
            owner.append(np.full(len(table), k))
            start.append(np.arange(len(table)))
        keys, owner, start = np.concatenate(keys), np.concatenate(owner), np.concatenate(start)
        self.keys, first, number = np.unique(keys, return_index=True, return_inverse=True)
        self.owner, self.start = owner[first], start[first]
        sizes = np.array([min(self.window, len(s)) for s in self.sequences], np.int64)
        self.length = sizes[self.owner]
        # a shorter window ends with the last suffix that begins with it
        self.ends = self.keys.copy()
        for k in np.flatnonzero(self.length < self.window):
            w = 4 * int(self.length[k])
            self.ends[k] = bytes(self.keys[k]).ljust(w, b"\0") + b"\xff" * (4 * self.window - w)
        pairs = np.unique(np.stack([number.ravel(), owner]), axis=1) if len(keys) else np.zeros((2, 0), np.int64)
        self.of_key = np.split(pairs[1], np.searchsorted(pairs[0], np.arange(1, len(self.keys)))) if len(self.keys) else []
        self.lead = min(3, int(sizes.min(initial=3))) or 1
        grams = [_lead_codes(s, self.lead) for s in self.sequences if len(s) >= self.lead]
        self.leads = np.unique(np.concatenate(grams)) if grams else np.zeros(0, np.uint64)

    def items_of(self, keys: np.ndarray) -> list[int]:
        """The ids of all items that hold any of the windows, sorted."""
        found = np.unique(np.concatenate([self.of_key[k] for k in np.unique(keys)]))
        return np.unique(np.concatenate([self.items[k] for k in found])).tolist()


def _packed(rows: np.ndarray, width: int) -> np.ndarray:
    """Rows of word numbers as byte strings that sort like the rows."""
    return np.ascontiguousarray(rows[:, :width], dtype=">u4").view(f"S{4 * width}").ravel()


def _lead_codes(seq: np.ndarray, lead: int) -> np.ndarray:
    out = np.zeros(len(seq) - lead + 1, np.uint64)
    for j in range(lead):
        out = out * np.uint64(0x9E3779B97F4A7C15) + seq[j : len(seq) - lead + 1 + j].astype(np.uint64)
    return out


def make_block(rows: list[tuple[int, str]], window: int) -> TestBlock:
    """Test items (id, text) as a block; items without words have nothing to find."""
    hashed = []
    for _, bounds, words in words_of(pa.array([t for _, t in rows], pa.string()), ALNUM):
        for a, b in zip(bounds[:-1], bounds[1:], strict=True):
            hashed.append(words[a:b])
    vocabulary = np.unique(np.concatenate(hashed)) if hashed else np.zeros(0, np.uint64)
    same: dict[bytes, tuple[np.ndarray, list[int]]] = {}
    for (item, _), h in zip(rows, hashed, strict=True):
        if len(h):
            same.setdefault(h.tobytes(), (h, []))[1].append(item)
    sequences = [np.searchsorted(vocabulary, h).astype(np.int64) + 1 for h, _ in same.values()]
    return TestBlock(vocabulary, [np.unique(np.array(ids, np.int64)) for _, ids in same.values()], sequences, window)


def test_blocks(benchmark: DataFrame, window: int, max_bytes: int = 4 << 20) -> Iterator[TestBlock]:
    """The benchmark (item_id, text) in blocks of about ``max_bytes`` of text, made one after the other."""
    held, size = [], 0
    for row in benchmark.where("item_id is not null").select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text")).toLocalIterator():
        held.append((row.item_id, row.text))
        size += len(row.text)
        if size >= max_bytes:
            yield make_block(held, window)
            held, size = [], 0
    if held:
        yield make_block(held, window)


def shard_matches(words: np.ndarray, bounds: np.ndarray, block: TestBlock) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Window hits in one shard: (document, first word, key) of each.

    ``words`` are the hashes of all documents of the shard, ``bounds`` the
    first word of each and the end.
    """
    none = (np.zeros(0, np.int64),) * 3
    if not len(block.keys) or not len(words):
        return none
    at = np.searchsorted(block.vocabulary, words)
    at[at == len(block.vocabulary)] = 0
    number = np.where(block.vocabulary[at] == words, at + 1, _GUARD)
    lead = block.lead
    if len(number) < lead:
        return none
    can = np.isin(_lead_codes(number, lead), block.leads)
    begin = np.flatnonzero(can)
    doc = np.searchsorted(bounds, begin, side="right") - 1
    keep = begin + lead <= bounds[doc + 1]
    begin, doc = begin[keep], doc[keep]
    if not len(begin):
        return none
    place = begin[:, None] + np.arange(block.window)[None, :]
    inside = place < bounds[doc + 1][:, None]
    suffix = _packed(np.where(inside, number[np.minimum(place, len(number) - 1)], _GUARD), block.window)
    order = np.argsort(suffix, kind="stable")
    suffix, begin, doc = suffix[order], begin[order], doc[order]
    low = np.searchsorted(suffix, block.keys, side="left")
    reps = np.maximum(np.searchsorted(suffix, block.ends, side="right") - low, 0)
    which = np.repeat(np.arange(len(reps)), reps)
    pos = low[which] + (np.arange(len(which)) - np.repeat(np.cumsum(reps) - reps, reps))
    return doc[pos], begin[pos], which


def _found_in(column: pa.Array, block: TestBlock) -> Iterator[tuple[int, list[dict], list[int]]]:
    """Words, longest matches and items of every text of an Arrow column."""
    for _, bounds, words in words_of(column, ALNUM):
        doc, first, key = shard_matches(words, bounds, block)
        order = np.argsort(doc, kind="stable")
        doc, first, key = doc[order], first[order], key[order]
        cut = np.searchsorted(doc, np.arange(len(bounds)))
        for d in range(len(bounds) - 1):
            a, b = cut[d], cut[d + 1]
            n = int(bounds[d + 1] - bounds[d])
            yield (n, _longest(first[a:b] - bounds[d], key[a:b], block), block.items_of(key[a:b])) if b > a else (n, [], [])


_SPANS = pa.list_(pa.struct([("first", pa.int64()), ("words", pa.int64()), ("item_id", pa.int64()), ("item_first", pa.int64())]))
_FOUND = "n_words long, matches array<struct<first:long,words:long,item_id:long,item_first:long>>, items array<long>"


def _matches(shared, keys: int):
    """The columns before the text, and what is found in the text."""

    def run(batches):
        for batch in batches:
            found = list(_found_in(batch.column(keys), shared.value))
            told = [pa.array([f[k] for f in found], kind) for k, kind in enumerate((pa.int64(), _SPANS, pa.list_(pa.int64())))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:keys], *told], [*batch.schema.names[:keys], "n_words", "matches", "items"])

    return run


def _longest(first: np.ndarray, key: np.ndarray, block: TestBlock) -> list[dict]:
    """Window hits of one text that follow each other in it and in the item, joined to longest verbatim matches."""
    length, item, start = block.length[key], block.owner[key], block.start[key]
    order = np.lexsort((first, first - start, item))
    first, length, item, start = first[order], length[order], item[order], start[order]
    new = np.ones(len(first), bool)
    new[1:] = (item[1:] != item[:-1]) | (first[1:] - start[1:] != first[:-1] - start[:-1]) | (first[1:] != first[:-1] + 1)
    at = np.flatnonzero(new)
    end = np.append(at[1:], len(first)) - 1
    return [{"first": int(first[a]), "words": int(first[e] + length[e] - first[a]), "item_id": int(block.items[item[a]][0]), "item_first": int(start[a])} for a, e in zip(at, end, strict=True)]


def _key() -> list:
    """What a text is known by between passes: its id and two hashes."""
    return [F.col("doc_id").cast("long").alias("id_"), F.xxhash64("text").alias("t1_"), F.xxhash64(F.lit("text"), "text").alias("t2_")]


def _same_text(left: DataFrame, right: DataFrame):
    return left["id_"].eqNullSafe(right["r_id_"]) & (left["t1_"] == right["r_t1_"]) & (left["t2_"] == right["r_t2_"])


def _found_by_block(docs: DataFrame, blocks: Iterator[TestBlock]) -> DataFrame:
    """(r_id_, r_t1_, r_t2_, n_words, matches, items) of the texts with a match, one pass for each block; its broadcast is destroyed after the pass."""
    keyed, parts = docs.where(F.col("text").isNotNull()).select(*_key(), "text"), None
    for block in blocks:
        shared = docs.sparkSession.sparkContext.broadcast(block)
        part = cut_lineage(keyed.mapInArrow(_matches(shared, 3), f"id_ long, t1_ long, t2_ long, {_FOUND}").where("size(items) > 0").dropDuplicates(["id_", "t1_", "t2_"]))
        shared.destroy()
        parts = part if parts is None else parts.union(part)
    joined = parts.groupBy("id_", "t1_", "t2_").agg(F.max("n_words").alias("n_words"), F.flatten(F.collect_list("matches")).alias("matches"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    return joined.withColumnsRenamed({c: f"r_{c}" for c in ("id_", "t1_", "t2_")})


def _first_two(blocks: Iterator[TestBlock], window: int) -> tuple[TestBlock, TestBlock | None]:
    return next(blocks, None) or make_block([], window), next(blocks, None)


def find_matches(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = 4 << 20) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_words, matches, items.

    ``matches`` lists longest verbatim matches that hold a window (first word
    and number of words in the document, an item and its first word there); they
    cover all words of all windows, each window told at the first place among the
    items that has it.  ``items`` lists all test items with a window in the
    text.  A window is ``window`` consecutive words of an item, or all words of a
    shorter one.  Null and empty texts have no words and no matches; an empty
    benchmark matches nothing, and items without id or words are passed over; an
    item that is there many times is one; rows with a null id keep it, repeated
    rows are searched each; other columns are ignored.
    """
    context = docs.sparkSession.sparkContext
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    blocks = test_blocks(benchmark, window, block_bytes)
    first, second = _first_two(blocks, window)
    if second is None:
        return texts.mapInArrow(_matches(context.broadcast(first), 1), f"doc_id long, {_FOUND}")
    found = _found_by_block(texts, chain([first, second], blocks)).drop("n_words")
    none = context.broadcast(make_block([], window))
    counted = texts.select(F.struct("doc_id", *_key()).alias("row"), "text").mapInArrow(_matches(none, 1), f"row struct<doc_id:long,id_:long,t1_:long,t2_:long>, {_FOUND}").select("row.*", "n_words")
    met = counted.join(found, _same_text(counted, found), "left")
    empty = lambda c: F.coalesce(c, F.array().cast(found.schema[c].dataType)).alias(c)
    return met.select("doc_id", "n_words", empty("matches"), empty("items"))


def hit_words(matches):
    """How many words lie inside any match, counting each once."""
    ordered = F.array_sort(F.transform(matches, lambda m: F.struct(m["first"].alias("a"), (m["first"] + m["words"]).alias("b"))))
    merged = F.aggregate(
        ordered,
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("end")),
        lambda s, m: F.struct((s["n"] + F.greatest(m["b"] - F.greatest(m["a"], s["end"]), F.lit(0))).alias("n"), F.greatest(s["end"], m["b"]).alias("end")),
    )
    return merged["n"]


def judged(matches: DataFrame, share: int = 20) -> DataFrame:
    """Adds n_hit and ``contaminated``: some word is hit, and at least one in ``share`` words is."""
    counted = matches.withColumn("n_hit", hit_words(F.col("matches")))
    return counted.withColumn("contaminated", (F.col("n_hit") > 0) & (F.col("n_hit") * share >= F.col("n_words")))


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20, block_bytes: int = 4 << 20) -> DataFrame:
    """The rows of ``docs`` (all columns) that are not contaminated.

    With one block the decision is taken where the text is read, so documents
    are not shuffled.  Null texts, rows with a null id, repeated rows and an
    empty benchmark are treated as by ``find_matches``.
    """
    blocks = test_blocks(benchmark, window, block_bytes)
    first, second = _first_two(blocks, window)
    if second is not None:
        gone = judged(_found_by_block(docs, chain([first, second], blocks)), share).where("contaminated").select("r_id_", "r_t1_", "r_t2_")
        id_, t1, t2 = (F.col("doc_id").cast("long"), F.xxhash64("text"), F.xxhash64(F.lit("text"), "text"))
        return docs.join(gone, id_.eqNullSafe(F.col("r_id_")) & (t1 == F.col("r_t1_")) & (t2 == F.col("r_t2_")), "left_anti")
    shared = docs.sparkSession.sparkContext.broadcast(first)
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            keep = []
            for _, bounds, words in words_of(batch.column(at), ALNUM):
                _, first_word, key = shard_matches(words, bounds, shared.value)
                cover = np.zeros(len(words) + 1, np.int64)
                np.add.at(cover, first_word, 1)
                np.add.at(cover, first_word + shared.value.length[key], -1)
                hit = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
                n_hit, n = hit[bounds[1:]] - hit[bounds[:-1]], np.diff(bounds)
                keep.append(~((n_hit > 0) & (share * n_hit >= n)))
            yield batch.filter(pa.array(np.concatenate(keep))) if keep else batch

    return docs.mapInArrow(run, docs.schema)
