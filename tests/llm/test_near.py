"""Line dedup, n-gram join and decontamination against brute force and odd rows."""

from __future__ import annotations

import random
import re
import time

import numpy as np
import pyarrow as pa
import pytest

from sparsegrid.llm import decontaminate as de
from sparsegrid.llm.graph import components
from sparsegrid.llm.line_dedup import dedup_lines, line_counts
from sparsegrid.llm.ngram_join import link_counts, ngram_components, ngram_links, shingle_sets
from sparsegrid.llm.textkernel import ALNUM, SLICE_BYTES, SPACED, words_of

ODD = [(1, None), (2, ""), (3, "  \t\n "), (None, "a b c d e f"), (4, "one two"), (4, "one two"), (5, "x " * 3000)]
SPACES = re.compile(r"[^\x20\x09-\x0D]+")


def words_by_regex(text):
    return SPACES.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def test_kernel_finds_the_same_words():
    rng = random.Random(1)
    texts = ["", None, "Ab aB é\tÉ  x", *["".join(rng.choice("aAb é\n\t.1-") for _ in range(rng.randrange(60))) for _ in range(400)]]
    seen = {}
    at = 0
    for i, bounds, h in words_of(pa.array(texts, pa.string()), SPACED):
        for k in range(len(bounds) - 1):
            mine = h[bounds[k] : bounds[k + 1]].tolist()
            want = words_by_regex(texts[i + k])
            assert len(mine) == len(want)
            for a, b in zip(mine, want, strict=True):
                assert seen.setdefault(b, a) == a
            at += 1
    assert at == len(texts) and len(set(seen.values())) == len(seen)


@pytest.mark.parametrize("letters", [SPACED, ALNUM])
def test_long_texts_are_hashed_whole(letters):
    one = "Wörter und words 12 " * (SLICE_BYTES // 8)
    got = [(b, h) for _, b, h in words_of(pa.array(["a", one, "b"]), letters)]
    assert sum(len(h) for _, h in got) == 2 + 4 * (SLICE_BYTES // 8)
    long = next(h for b, h in got if len(h) > 10)
    assert len(np.unique(long)) == 4
    assert sum(len(h) for _, _, h in words_of(pa.array(["x" * (3 * SLICE_BYTES)]), letters)) == 1


def brute_components(rows, n, num, den):
    sets = {}
    for i, t in rows:
        w = words_by_regex(t)
        sets[i] = {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())
    ids, parent = list(sets), {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if den * both >= num * (len(sets[a]) + len(sets[b]) - both):
                    x, y = sorted((find(a), find(b)))
                    parent[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


def near_rows(seed, groups=6, size=25, words=60):
    rng = random.Random(seed)
    rows, k = [], 0
    passage = [f"p{j}" for j in range(25)]
    for g in range(groups):
        base = [f"w{rng.randrange(400)}" for _ in range(words)]
        for _ in range(size):
            own = list(base)
            for _ in range(rng.choice([0, 0, 1, 2, 3, 6])):
                own[rng.randrange(len(own))] = f"e{rng.randrange(10**6)}"
            if rng.random() < 0.2:
                own = own[: rng.randrange(5, words)] + passage
            rows.append((k, " ".join(own)))
            k += 1
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("seed,small,few", [(1, 32, 200_000), (2, 2, 0), (3, 4, 200_000), (4, 1, 0)])
def test_components_equal_brute_force(docs_of, seed, small, few):
    rows = near_rows(seed)
    got = {r.doc_id: (r["size"], r.component) for r in ngram_components(docs_of(rows), 4, 85, 100, small=small, few=few).collect()}
    assert got == brute_components(rows, 4, 85, 100)


def test_one_large_group_of_near_copies(docs_of):
    rows = near_rows(4, groups=1, size=120, words=80)
    got = {r.doc_id: (r["size"], r.component) for r in ngram_components(docs_of(rows), small=8).collect()}
    assert got == brute_components(rows, 5, 80, 100)


def test_join_of_odd_rows(docs_of):
    rows = sorted((str(r.doc_id), r["size"], str(r.component)) for r in ngram_components(docs_of(ODD), 4, 85, 100).collect())
    assert rows == sorted([("1", 0, "1"), ("2", 0, "2"), ("3", 0, "3"), ("None", 3, "None"), ("4", 1, "4"), ("4", 1, "4"), ("5", 1, "5")])
    assert ngram_components(docs_of([]), 4, 85, 100).count() == 0


def test_shingles_of_short_texts():
    sizes = [len(s) for s in shingle_sets(pa.array(["", "a", "a b c", "a b c d", "a b a b a b", None]), 4)]
    assert sizes == [0, 1, 1, 1, 2, 0]


def test_components_of_a_long_path(spark):
    n = 200
    links = spark.createDataFrame([(k + 1, k) for k in range(n)] + [(1000, 1001)], "a bigint, b bigint")
    got = {r.vertex: r.label for r in components(links).collect()}
    assert got == {k: 0 for k in range(n + 1)} | {1000: 1000, 1001: 1000}


def brute_lines(rows, least):
    """Kept, near and all lines by the definition."""
    first = {}
    for i, t in sorted((r for r in rows if r[0] is not None and r[1] is not None), key=lambda r: r[0]):
        for k, line in enumerate(t.split("\n")):
            w = tuple(SPACES.findall(line))
            if w:
                first.setdefault(w, (i, k))

    def close(a, b):
        if abs(len(a) - len(b)) > 1 or a == b:
            return False
        d = list(range(len(b) + 1))
        for x in a:
            e = [d[0] + 1]
            for j, y in enumerate(b):
                e.append(min(d[j] + (x != y), d[j + 1] + 1, e[j] + 1))
            d = e
        return d[-1] <= 1

    near = {w for w, at in first.items() if len(w) >= least and any(len(v) >= least and first[v] < at and close(w, v) for v in first)}
    return {first[w]: w in near for w in first}


def line_rows(seed):
    rng = random.Random(seed)
    lines = [" ".join(f"w{rng.randrange(40)}" for _ in range(rng.choice([3, 7, 8, 9, 14]))) for _ in range(40)]
    rows = []
    for i in range(60):
        own = []
        for _ in range(rng.randrange(1, 6)):
            w = rng.choice(lines).split()
            kind = rng.random()
            if kind < 0.2:
                w[rng.randrange(len(w))] = f"n{rng.randrange(9)}"
            elif kind < 0.3:
                w.pop(rng.randrange(len(w)))
            elif kind < 0.4:
                w.insert(rng.randrange(len(w) + 1), "more")
            own.append(rng.choice([" ", "  "]).join(w))
        rows.append((i, "\n".join([*own, ""])))
    return rows


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_line_dedup_equals_brute_force(docs_of, seed):
    rows = line_rows(seed)
    want = brute_lines(rows, 8)
    got = {r.doc_id: r for r in line_counts(docs_of(rows)).collect()}
    text = {r.doc_id: r.text for r in dedup_lines(docs_of(rows)).collect()}
    for i, t in rows:
        lines = t.split("\n")
        stays = [line for k, line in enumerate(lines) if not line.strip() or want.get((i, k)) is False]
        assert text[i] == "\n".join(stays)
        assert got[i].n_near == sum(want.get((i, k)) is True for k in range(len(lines)))
        assert got[i].n_lines == got[i].n_blank + got[i].n_kept + got[i].n_near + got[i].n_exact


@pytest.mark.parametrize("many", [3, 1_000_000])
def test_rows_that_share_an_id_are_told_apart(docs_of, many):
    """Repeated ids with other texts, repeated rows, near copies under one id, and keys that many lines share."""
    rng = random.Random(11)
    base = " ".join(f"w{k}" for k in range(12))
    rows = [(7, "\n".join([base, base.replace("w5", "other"), f"own line {k}"])) for k in range(4)] + [(7, "own line 1")] * 2
    rows += [(k % 9, base.replace(f"w{k % 12}", f"x{rng.randrange(5)}")) for k in range(60)]
    rows += [(1, f"{base}\n\n{base}"), (None, base), (3, None)]
    order = lambda r: (r[0], hashes[r[1]])
    docs = docs_of(rows)
    hashes = {r.text: r.h for r in docs.selectExpr("text", "xxhash64(text) AS h").collect()}
    own = sorted({r for r in rows if r[0] is not None and r[1] is not None}, key=order)
    want = brute_lines([(i, t) for i, (_, t) in enumerate(own)], 8)
    stays = {r: "\n".join(line for k, line in enumerate(r[1].split("\n")) if not line.strip() or want.get((i, k)) is False) for i, r in enumerate(own)}
    expected = sorted((str(i), str(stays.get((i, t), t))) for i, t in rows)
    assert sorted((str(r.doc_id), str(r.text)) for r in dedup_lines(docs, many=many).collect()) == expected
    counts = line_counts(docs, many=many).collect()
    assert len(counts) == len(rows) and all(min(r.n_kept, r.n_near, r.n_exact, r.n_blank) >= 0 for r in counts)


def test_line_dedup_of_odd_rows(docs_of):
    docs = docs_of(ODD)
    out = dedup_lines(docs)
    assert out.columns == docs.columns
    assert sorted((str(r.doc_id), str(r.text)) for r in out.collect()) == sorted((str(i), str(t)) for i, t in ODD)
    assert line_counts(docs_of([])).count() == 0
    counts = {r.doc_id: tuple(r)[1:] for r in line_counts(docs).collect()}
    assert counts[1] == (0, 0, 0, 0, 0) and counts[2] == (1, 1, 0, 0, 0) and counts[None] == (1, 0, 1, 0, 0)


def test_a_very_long_line(docs_of):
    long = " ".join(f"v{k}" for k in range(30_000))
    rows = [(1, long), (2, long.replace("v777 ", "other ")), (3, long.replace("v777 ", "")), (4, long + " x y")]
    got = {r.doc_id: (r.n_kept, r.n_near) for r in line_counts(docs_of(rows)).collect()}
    assert got == {1: (1, 0), 2: (0, 1), 3: (0, 1), 4: (1, 0)}


def test_a_text_of_very_many_near_lines(docs_of):
    words = [f"v{k}" for k in range(9)]
    near = "\n".join(" ".join([*words, f"n{k}"]) for k in range(32_000))
    began = time.monotonic()
    assert [(r.n_kept, r.n_near) for r in line_counts(docs_of([(1, near)])).collect()] == [(1, 31_999)]
    assert dedup_lines(docs_of([(1, near)])).first().text == " ".join([*words, "n0"])
    assert time.monotonic() - began < 60


ITEM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute_hits(docs, items, window):
    low = lambda t: ITEM.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
    wins = [(i, tuple(w[k : k + min(window, len(w))])) for i, t in items if (w := low(t)) for k in range(len(w) - min(window, len(w)) + 1)]
    out = {}
    for d, t in docs:
        w = low(t)
        hit, found = set(), set()
        for i, g in wins:
            for k in range(len(w) - len(g) + 1):
                if tuple(w[k : k + len(g)]) == g:
                    hit |= set(range(k, k + len(g)))
                    found.add(i)
        out[d] = (len(w), len(hit), sorted(found))
    return out


@pytest.mark.parametrize("seed,block", [(1, 1 << 20), (2, 60), (3, 1)])
def test_decontamination_equals_brute_force(spark, docs_of, seed, block):
    rng = random.Random(seed)
    word = lambda: rng.choice(["a", "b", "é", "C", "d9"])
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([1, 2, 5, 6, 7, 12, 0])]
    docs = [(i, ", ".join(word() for _ in range(rng.randrange(30)))) for i in range(40)] + [(90, None), (91, "")]
    bench = spark.createDataFrame([*items, (None, "a a"), (77, None)], "item_id bigint, text string")
    found = de.judged(de.find_matches(docs_of(docs), bench, 5, block)).collect()
    got = {r.doc_id: (r.n_words, r.n_hit, sorted(r["items"])) for r in found}
    assert got == brute_hits(docs, items, 5)
    kept = {r.doc_id for r in de.remove_contaminated(docs_of(docs), bench, 5, 20, block).collect()}
    assert kept == {d for d, (n, h, _) in got.items() if not (h and 20 * h >= n)}


def test_matches_are_longest_and_placed(spark, docs_of):
    bench = spark.createDataFrame([(5, "one two three four five six seven")], "item_id bigint, text string")
    docs = docs_of([(1, "x Two, three four FIVE six y one two three four")])
    m = de.find_matches(docs, bench, 4).first()
    assert [tuple(x) for x in m.matches] == [(1, 5, 5, 1), (7, 4, 5, 0)] and m.n_words == 11


def test_decontamination_of_odd_rows(spark, docs_of):
    none = spark.createDataFrame([], "item_id bigint, text string")
    assert de.find_matches(docs_of(ODD), none).count() == len(ODD)
    assert de.remove_contaminated(docs_of(ODD), none).count() == len(ODD)
    assert de.find_matches(docs_of([]), none).count() == 0


def test_members_of_groups_that_are_linked_though_their_leads_are_not(docs_of):
    """Same prefixes and sizes, but the links run between other members than the first."""
    rng = random.Random(8)
    common = [f"c{k}" for k in range(60)]
    rows = [(100 + k, " ".join(common[j] for j in rng.sample(range(60), 60))) for k in range(30)]  # makes the words frequent
    rare = [f"r{k}" for k in range(8)]
    for g in range(12):
        tail = [common[(g * 5 + j) % 60] for j in range(30)]
        for k in range(3):
            own = list(tail)
            own[7 * k : 7 * k + k] = own[7 * k : 7 * k + k][::-1]
            rows.append((g * 3 + k, " ".join(rare + own)))
    for small in (1, 32):
        got = {r.doc_id: (r["size"], r.component) for r in ngram_components(docs_of(rows), 2, 60, 100, small=small).collect()}
        assert got == brute_components(rows, 2, 60, 100)


def test_an_id_with_several_texts_is_one_document(docs_of):
    base = [f"w{k}" for k in range(40)]
    other = [f"v{k}" for k in range(40)]
    rows = [(1, " ".join(base)), (5, " ".join([*base, "x"])), (5, " ".join(other)), (3, " ".join([*other, "y"])), (9, "alone in the world")]
    got = sorted((r.doc_id, r.component) for r in ngram_components(docs_of(rows)).collect())
    assert got == [(1, 1), (3, 1), (5, 1), (5, 1), (9, 9)]


def test_components_of_a_random_graph(spark):
    rng = random.Random(3)
    links = [(rng.randrange(400), rng.randrange(400)) for _ in range(330)]
    got = {r.vertex: r.label for r in components(spark.createDataFrame(links, "a bigint, b bigint").repartition(7)).collect()}
    label = {v: v for e in links for v in e}
    for _ in range(400):
        for a, b in links:
            label[a] = label[b] = min(label[a], label[b])
    assert got == {v: k for v, k in label.items() if any(v in e and e[0] != e[1] for e in links)}


def test_many_equal_items_are_searched_once(spark, docs_of):
    """400 equal one-word items, items of one repeated word, and a text of 20,000 words."""
    bench = spark.createDataFrame([(k, "a") for k in range(400)] + [(400, "b " * 40), (401, "b " * 13)], "item_id bigint, text string")
    began = time.monotonic()
    out = de.judged(de.find_matches(docs_of([(1, "a " * 20_000), (2, "c " + "b " * 5_000), (3, "b " * 12)]), bench)).collect()
    assert [(r.n_words, r.n_hit, len(r["items"])) for r in out] == [(20_000, 20_000, 400), (5_001, 5_000, 2), (12, 0, 0)]
    assert sum(len(r.matches) for r in out) <= 25_000 and time.monotonic() - began < 20


def test_blocks_are_passed_one_after_the_other(spark, docs_of):
    bench = spark.createDataFrame([(1, "one two three"), (2, "four five"), (3, "one two three")], "item_id bigint, text string")
    rows = [(1, "x one two three four five"), (1, "x one two three four five"), (1, "four five"), (None, "four five six"), (7, None), (8, "")]
    tell = lambda size: sorted((str(r.doc_id), r.n_words, r.n_hit, tuple(r["items"])) for r in de.judged(de.find_matches(docs_of(rows), bench, 3, size)).collect())
    assert tell(1) == tell(1 << 20) == sorted([("1", 6, 5, (1, 2, 3))] * 2 + [("1", 2, 2, (2,)), ("None", 3, 2, (2,)), ("7", 0, 0, ()), ("8", 0, 0, ())])
    kept = lambda size: sorted(str(r.doc_id) for r in de.remove_contaminated(docs_of(rows), bench, 3, 20, size).collect())
    assert kept(1) == kept(1 << 20) == ["7", "8"]


@pytest.mark.parametrize("seed,few", [(1, 0), (5, 200_000)])
def test_links_equal_brute_force(docs_of, seed, few):
    """Every link between different texts, and how many each row has."""
    rows = near_rows(seed, groups=4, size=20)
    rows += [(1000 + k, t) for k, (_, t) in enumerate(rows[:15])] + [(2000, None), (2001, ""), (None, rows[0][1])]
    sets = {}
    for i, t in rows:
        w = words_by_regex(t)
        if i is not None and w:
            sets[i] = frozenset(tuple(w[k : k + 4]) for k in range(len(w) - 3)) if len(w) >= 4 else frozenset([tuple(w)])
    linked = lambda a, b: 100 * len(a & b) >= 85 * len(a | b)
    links, members = ngram_links(docs_of(rows), 4, 85, 100, few)
    named = {s: min(i for i, o in sets.items() if o == s) for s in set(sets.values())}
    want = {tuple(sorted((named[a], named[b]))) for a in named for b in named if a != b and linked(a, b)}
    got = [tuple(r) for r in links.collect()]
    assert len(got) == len(set(got)) and set(got) == want
    counts = {r.doc_id: (r.class_id, r.n_links) for r in link_counts(links, members).collect()}
    assert counts == {i: (named[s], sum(linked(s, o) for j, o in sets.items() if j != i)) for i, s in sets.items()}
    assert ngram_links(docs_of([]))[0].count() == 0
