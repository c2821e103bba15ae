"""Classifiers by held-out accuracy; personal data and formats against brute force and round trips."""

from __future__ import annotations

import hashlib
import itertools
import random
import re
import time

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from sparsegrid.llm import chroma as ch
from sparsegrid.llm import personal as pe
from sparsegrid.llm import toxicity as tx
from sparsegrid.llm.chat import digests, fold_events, read_back, render, table_as_log
from sparsegrid.llm.mixing import draw_slots, mix_sources, mixed_corpus, permuted, taken_words
from sparsegrid.llm.quality import features, keep_good, score_quality, train_quality
from sparsegrid.llm.sampling import labelled_sample
from sparsegrid.llm.url_rules import Rule, judge_urls, labelled_pages, listed_rules, mine_rules, url_tokens, with_parts

SF = "/root/testdata/sf0.01"
ODD = [(1, None), (2, ""), (3, "  \t\n "), (None, "a b c"), (4, "one two"), (4, "one two"), (5, "x" * 200_000)]


@pytest.fixture(scope="module")
def tables(spark):
    return {t: spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels", "pages", "conversations", "embeddings")}


def test_quality_held_out(tables):
    model = train_quality(tables["documents"], tables["labels"])
    scored = score_quality(tables["documents"], model).join(tables["labels"], "doc_id").where(F.crc32(F.col("doc_id").cast("string")) % 5 == 0)
    rows = scored.select((F.col("score") >= 0.3).cast("int").alias("p"), "quality").collect()
    assert len(rows) > 50 and np.mean([r.p == r.quality for r in rows]) >= 0.95


def test_quality_of_odd_rows(spark, docs_of, tables):
    model = train_quality(tables["documents"], tables["labels"])
    out = score_quality(docs_of(ODD), model).collect()
    assert len(out) == len(ODD) and all(0 <= r.score <= 1 for r in out)
    assert len({r.score for r in out if r.doc_id in (1, 2, 3)}) == 1
    kept = keep_good(docs_of(ODD), model, 0.0)
    assert kept.columns == docs_of(ODD).columns and kept.count() == len(ODD)
    assert score_quality(docs_of([]), model).count() == 0
    nothing = train_quality(docs_of([]), spark.createDataFrame([], "doc_id bigint, quality int"))
    assert {r.score for r in score_quality(docs_of(ODD), nothing).collect()} == {0.5}


def test_a_very_long_text_does_not_empty_the_sample(spark, docs_of, tables):
    """18 MB under the smallest id, one label each way, and an id with several texts."""
    rows = [(k, ("good words in order " if k % 2 else "!! !! spam ") * (3 + k % 5)) for k in range(2, 60)] + [(1, "w " * (9 << 20)), (2, "shorter"), (3, None)]
    labels = spark.createDataFrame([(k, k % 2, 1 - k % 2) for k in range(60)] + [(4, 1, None), (None, 1, 1)], "doc_id bigint, quality int, toxic int")
    docs = docs_of(rows)
    got = labelled_sample(docs, labels, "quality", (5, 0), 3000, 16 << 20, 11).collect()
    ids = sorted(r.doc_id for r in got)
    assert len(ids) == len(set(ids)) and 35 <= len(ids) <= 58 and sum(len(r.text) for r in got) <= 16 << 20
    assert {r.doc_id: r.text for r in got}.get(2, "shorter") == "shorter" and all(r.label == 1 for r in got if r.doc_id == 4)
    only = labelled_sample(docs.where("doc_id = 1"), labels, "quality", (5, 0), 10, 1 << 20, 11).collect()
    assert [r.doc_id for r in only] in ([1], []), "the only text of a class is taken whatever its length"
    model = train_quality(docs, labels)
    scores = {r.doc_id: r.score for r in score_quality(docs, model).collect()}
    assert scores[7] > 0.7 > 0.3 > scores[8]


def test_features_do_not_depend_on_neighbours():
    texts = ["a b b!! c", "", None, "é" * 50 + " %% x", "a b b!! c"]
    together = list(features(pa.array(texts)))
    alone = [next(iter(features(pa.array([t], pa.string())))) for t in texts]
    for (s, v), (s1, v1) in zip(together, alone, strict=True):
        assert s.tolist() == s1.tolist() and v.tolist() == v1.tolist()


def test_toxicity_held_out(tables):
    model = tx.train_toxicity(tables["documents"], tables["labels"])
    scored = tx.score_toxicity(tables["documents"], model).join(tables["labels"], "doc_id").where(F.crc32(F.col("doc_id").cast("string")) % 3 == 1)
    rows = scored.select("score", "toxic").collect()
    hits = [r.score >= 0.7 for r in rows if r.toxic]
    false = [r.score >= 0.7 for r in rows if not r.toxic]
    assert np.mean(hits) >= 0.6 and np.mean(false) <= 0.03


def test_toxicity_shares_subwords():
    rng = random.Random(2)
    word = lambda: "".join(rng.choice("bdfglnprtaeiou") for _ in range(rng.randint(3, 8)))
    clean = [" ".join(word() for _ in range(60)) for _ in range(200)]
    bad = [" ".join([*(word() for _ in range(30)), rng.choice(["vexkwhy", "zumzumz"]), *(word() for _ in range(30))]) for _ in range(80)]
    score = tx.fit_subwords(clean + bad, [0] * 200 + [1] * 80).scorer().score
    plain = " ".join(word() for _ in range(40))
    assert score(plain) < 0.3 < 0.7 < score(f"{plain} vexkwhy {plain}")
    assert score(f"{plain} vexkwhyy {plain}") > 0.5, "a misspelling that was never seen"
    assert abs(score(f"{plain} vexkwhy {plain}") - score(f"{plain} {plain} {plain} vexkwhy {plain}")) < 0.3, "long texts do not thin it out"


def test_toxicity_of_odd_rows(docs_of):
    model = tx.fit_subwords(["a b", "c d"], [0, 1])
    out = tx.score_toxicity(docs_of(ODD), model).collect()
    assert len(out) == len(ODD) and all(0 <= r.score <= 1 for r in out)
    assert tx.fit_subwords([], []).scorer().score("x") == 0.5
    assert tx.subwords(["", "ab"])[1].tolist().count(0) == 0


BASE = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def brute_base(text):
    out = []
    for k, kind in enumerate(pe.BASE_KINDS):
        for m in BASE[kind].finditer(text):
            digits = re.sub("[^0-9]", "", m[0])
            fits = {
                "email": True,
                "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else True,
                "card": 13 <= len(digits) <= 19 and pe.luhn(digits),
                "phone": 9 <= len(digits) <= 15,
            }[kind]
            if fits:
                out.append((k, m.start(), m.end()))
    return out


def test_base_spans_equal_the_patterns():
    rng = random.Random(7)
    parts = ["a.b@c.de", "@", "x@y", "1.2.3.4", "300.1.1.1", "0007.8.9.1", "4111 1111 1111 1111", "4111-1111-1111-1111 4111", "+1 (017) 555-7713", "+12", "é", " ", ".", "-", "5", "@a.b", "+", "(", "a+b%c@d-e.f.g."]
    for _ in range(3000):
        text = "".join(rng.choice(parts) for _ in range(rng.randrange(8)))
        assert pe.base_spans(text) == brute_base(text), text


def test_field_finds_what_patterns_do_not():
    model = pe.train_field()
    told = lambda text: [(pe.KINDS[y], text[a:b]) for y, a, b in pe.all_spans(text, model)[1]]
    assert told("pay 7536784127813050 4845168114407329 now") == [("card", "7536784127813050"), ("card", "4845168114407329")]
    assert told('the token = "03dbebab91ab85687d33eeaaf9ac699e1188f962" is')[0][0] == "secret"
    assert told("call (017) 555-7713 today") == [("phone", "(017) 555-7713")]
    assert told("in 2024 we sold 12 of 30 for 9.99 on 3.4.2021") == []
    base, added = pe.all_spans("mail a.b@c.de or 1.2.3.4", model)
    assert len(base) == 2 and not added


def test_entities_are_not_cut_between_stretches():
    model = pe.train_field()
    told = lambda text: [(pe.KINDS[y], text[a:b]) for y, a, b in pe.all_spans(text, model)[1]]
    assert told("In 2024 please call our new office line (017) 555-7713 today") == [("phone", "(017) 555-7713")]
    secret = '"03dbebab91ab85687d33eeaaf9ac699e1188f962"'
    for pad in range(20, 60):
        before = ("words of no note at all and some more of them " * 2)[:pad]
        assert ("secret", secret) in told(f"in 2024 {before} api token = {secret} is it"), pad
        assert ("phone", "(017) 555-7713") in told(f"in 2024 {before} call (017) 555-7713 today"), pad
    many = "call (017) 555-7713 today or so, " * 400
    assert told(many) == [("phone", "(017) 555-7713")] * 400
    assert told("write to annabel at wonder dot com today") == [("email", "annabel at wonder dot com")]
    assert told("we looked at the dot on the wall and at a dot of ink") == []


def test_personal_of_odd_rows(docs_of):
    model = pe.train_field(60, 1)
    out = pe.find_personal(docs_of([*ODD, (6, "1" * 100_000), (7, "@" * 50_000), (8, "a@" * 20_000), (9, "+1 (" * 20_000)]), model).collect()
    assert len(out) == len(ODD) + 4 and pe.find_personal(docs_of([]), model).count() == 0


def test_scaled_fingerprints_and_search(spark):
    rng = np.random.default_rng(3)
    vectors = rng.normal(0, 1, (60, 64))
    late = np.concatenate([rng.normal(0, 1, 12), vectors[0][:52]])
    quiet = ch.decode_pcm(ch.encode_pcm(0.3 * ch.melody(vectors[20])))
    sounds = {k: ch.melody(v) for k, v in enumerate(vectors)} | {60: ch.melody(late), 61: quiet, 62: ch.melody(vectors[40]), 63: np.zeros(10)}
    media = spark.createDataFrame([(k, bytearray(ch.encode_pcm(s))) for k, s in sounds.items()] + [(64, None), (None, None)], "media_id bigint, media binary")
    prints = ch.fingerprints(media, "media_id", "media")
    rows = {r.media_id: r for r in ch.search_recordings(prints).collect()}
    codes = {r.media_id: np.array(r.codes, np.uint32) for r in prints.collect()}
    assert len(rows) == 66 and rows[63].n_codes == 0 and rows[63].class_id is None and rows[62].class_id == 40
    assert [m.match for m in rows[0].matches] == [60] and rows[0].matches[0].offset == 12
    assert [m.match for m in rows[20].matches] == [61] or rows[61].class_id == 20
    # brute force over all pairs of classes and offsets
    classes = sorted({r.class_id for r in rows.values() if r.class_id is not None})
    for q in (c for c in classes if rows[c].is_query):
        want = set()
        for r in classes:
            votes = {}
            for i, x in enumerate(codes[q]):
                for j in np.flatnonzero(codes[r] == x):
                    votes[j - i] = votes.get(j - i, 0) + 1
            if r != q and votes:
                best = max(votes, key=lambda o: (votes[o], -o))
                e, n = ch.bit_errors(codes[q], codes[r], best)
                if votes[best] >= 3 and n >= 16 and e <= 0.3 * 32 * n:
                    want.add((r, best))
        assert {(m.match, m.offset) for m in rows[q].matches} == want


def test_held_notes_repeats_and_odd_rows(spark):
    """Long runs of one code, an id with several sounds, clashing columns, an empty table."""
    rng = np.random.default_rng(8)
    tune = [int(c) for c in rng.integers(0, 1 << 32, 40)]
    rows = [(0, [7] * 32_000), (1, [7] * 31_990 + tune), (20, tune[:30] + [5] * 20), (3, [5] * 9 + tune), (4, []), (None, tune), (40, tune), (40, [9] * 30)]
    prints = spark.createDataFrame([(i, c, "x", 1) for i, c in rows], "media_id bigint, codes array<bigint>, matches string, class_id int")
    began = time.monotonic()
    got = {}
    for r in ch.search_recordings(prints, max_error=0.5).collect():
        got.setdefault(r.media_id, []).append(r)
    assert time.monotonic() - began < 40 and sum(map(len, got.values())) == len(rows)
    assert [(m.match, m.offset, m.votes) for m in got[0][0].matches] == [(1, -10, 31_990)]
    assert (3, 9, 30) in [(m.match, m.offset, m.votes) for m in got[20][0].matches]
    assert got[4][0].class_id is None and got[None][0].matches == []
    assert ch.search_recordings(prints.limit(0)).count() == 0


def brute_offset(x, y):
    votes = {}
    for i, p in enumerate(x):
        for j, q in enumerate(y):
            if p == q:
                votes[j - i] = votes.get(j - i, 0) + 1
    return max(((v, -o) for o, v in votes.items()), default=(0, 0))


def test_votes_of_runs_equal_votes_of_places():
    rng = random.Random(6)
    for _ in range(300):
        x, y = ([c for _ in range(rng.randrange(9)) for c in [rng.randrange(4)] * rng.randrange(1, 6)] for _ in range(2))
        v, o = ch.best_offset(np.array(x, np.int64), np.array(y, np.int64))
        assert (v, -o) == brute_offset(x, y)
    x, y = [k % 2 for k in range(300)], [k % 3 == 0 for k in range(200)]
    v, o = ch.best_offset(np.array(x, np.int64), np.array(y, np.int64))
    assert (v, -o) == brute_offset(x, y), "codes with very many runs"


@pytest.mark.parametrize("salt", [1, 4096])
def test_recordings_that_share_enough_codes(spark, salt):
    rng = random.Random(7)
    codes = {k: [rng.randrange(6) for _ in range(rng.randrange(8))] for k in range(30)}
    held = spark.createDataFrame([(k, k % 3 == 0, c) for k, c in codes.items()], "class_id bigint, asked boolean, codes array<bigint>")
    got = {(r.query, r.match) for r in ch._sharing(held, 2, salt).collect()}
    assert got == {(q, r) for q in range(0, 30, 3) for r in codes if q != r and sum(min(codes[q].count(c), codes[r].count(c)) for c in range(6)) >= 2}


def test_close_recordings_are_those_of_all_pairs(spark):
    rng = np.random.default_rng(5)
    vectors = rng.normal(0, 1, (40, 64))
    noisy = [ch.melody(vectors[0]) + rng.normal(0, s, 64 * ch.HOP) for s in (0.3, 1.0)]
    late = ch.melody(vectors[20])[256:]
    sounds = {k: ch.melody(v[: 64 - k % 3]) for k, v in enumerate(vectors)} | {40: noisy[0], 41: noisy[1], 42: late, 43: ch.melody(vectors[3][:30])}
    codes = {k: ch.fingerprint(ch.chroma_frames(s)) for k, s in sounds.items()}
    prints = spark.createDataFrame([(k, [int(c) for c in v]) for k, v in codes.items()] + [(44, []), (None, [1])], "media_id bigint, codes array<bigint>")
    rows = {r.media_id: r for r in ch.search_recordings(prints).collect()}
    for q in (0, 20, 40):
        want = []
        for r in (r for r in codes if r != q):
            tried = [(e / n, o, e, n) for o in range(-64, 65) for e, n in [ch.bit_errors(codes[q], codes[r], o)] if n >= 16]
            fits = [t for t in tried if t[2] <= 0.3 * 32 * t[3]]
            want += [(r, *min(fits)[1:])] if fits else []
        assert [tuple(m) for m in rows[q].close] == want
    missed = {(q, m.match) for q in (0, 20, 40) for m in rows[q].close} - {(q, m.match) for q in (0, 20, 40) for m in rows[q].matches}
    assert {m.match for m in rows[0].close} >= {40} and {m.match for m in rows[20].close} >= {42} and missed
    assert rows[44].close == [] and rows[None].close == [] and rows[1].close == []


def test_chat_round_trip(spark):
    rng = random.Random(5)
    bits = ["</s>", "[INST]", "<|turn|>", "<|end|>\n", "~", "~0", "~1", "é", "\n", " ", "ok", "assistant\n", "<"]
    rows = [(c, k, rng.choice(["user", "assistant", "system", "od~d\n<"]), "".join(rng.choice(bits) for _ in range(rng.randrange(9)))) for c in range(30) for k in range(rng.randrange(1, 6))]
    rows += [(100, 0, None, None), (100, 1, "assistant", None), (None, 0, "user", "x"), (101, 3, "user", "twice"), (101, 3, "user", "twice")]
    table = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    read = read_back(render(fold_events(table_as_log(table))))
    got = {r.conv_id: r for r in read.collect()}
    for c in {r[0] for r in rows}:
        want = [(r[2] or "", r[3] or "") for r in sorted((r for r in rows if r[0] == c), key=lambda r: r[1])]
        assert [(t.role, t.text) for t in got[c].turns] == want
        assert got[c].loss_text == "".join(t for role, t in want if role == "assistant")
    d = {r.conv_id: r for r in digests(read).collect()}
    assert d[101].n_turns == 2 and d[101].turns_sha256 == hashlib.sha256(b"user\ntwice\n" * 2).hexdigest()
    assert d[100].loss_chars == 0 and d[100].loss_sha256 == hashlib.sha256(b"").hexdigest()


def test_chat_events_fold(spark):
    log = [
        (1, 1, 0, "message", "user", "helo"), (1, 2, 1, "message", "assistant", ""), (1, 3, 1, "delta", None, "Hi "), (1, 4, 1, "delta", None, "there"),
        (1, 5, 0, "edit", "user", "hello"), (1, 6, 2, "message", "user", "more"), (1, 7, 1, "regenerate", "assistant", ""), (1, 8, 1, "delta", None, "Hey"), (1, 9, 2, "message", "user", "again"),
        (1, 10, 3, "message", "assistant", "gone"), (1, 11, 3, "delete", None, None), (2, 1, 0, None, "user", "x"), (2, 2, 1, "delta", "assistant", "y"),
    ]
    df = spark.createDataFrame(log, "conv_id bigint, seq bigint, turn bigint, kind string, role string, text string")
    got = sorted(map(tuple, fold_events(df).collect()))
    assert got == [(1, 0, "user", "hello"), (1, 1, "assistant", "Hey"), (1, 2, "user", "again"), (2, 0, "user", "x"), (2, 1, "assistant", "y")]


def replayed(log):
    """The final messages of one conversation, event after event."""
    held = {}
    for _, turn, kind, role, text in sorted(log, key=lambda e: (e[0], e[2] or "message", e[3] is not None, e[3] or "", e[4] is not None, e[4] or "")):
        if kind == "delete":
            held.pop(turn, None)
            continue
        if kind == "regenerate":
            held = {t: m for t, m in held.items() if t <= turn}
        old_role, old_text = held.get(turn, (None, ""))
        held[turn] = (role or old_role, (old_text if kind == "delta" else "") + (text or ""))
    return sorted((t, *m) for t, m in held.items())


def test_folds_equal_a_replay(spark):
    rng = random.Random(9)
    kinds = ["message", "delta", "delta", "edit", "regenerate", "delete", None]
    logs = {c: [(s, rng.randrange(4), rng.choice(kinds), rng.choice(["user", "assistant", None]), rng.choice(["a", "b ", "", None])) for s in range(rng.randrange(1, 14))] for c in range(120)}
    logs[500] = [(1, 0, "message", "user", "x"), (2, 0, "delete", None, None), (3, 0, "delta", "assistant", "back")]
    df = spark.createDataFrame([(c, *e) for c, log in logs.items() for e in log], "conv_id bigint, seq bigint, turn bigint, kind string, role string, text string")
    got = {}
    for r in fold_events(df).collect():
        got.setdefault(r.conv_id, []).append((r.turn, r.role, r.text))
    assert {c: sorted(m) for c, m in got.items()} == {c: m for c, log in logs.items() if (m := replayed(log))}


def test_logs_of_tables_fold_back(spark, tables):
    table = tables["conversations"]
    log = table_as_log(table)
    assert {r.kind for r in log.select("kind").distinct().collect()} == {"message", "delta", "edit", "regenerate", "delete"}
    rows = lambda df: sorted((r.conv_id, str(r.role), r.text) for r in df.collect())
    assert rows(fold_events(log)) == sorted((r.conv_id, str(r.role), r.text or "") for r in table.collect())
    empty = spark.createDataFrame([], table.schema)
    assert read_back(render(fold_events(table_as_log(empty)))).count() == 0


def test_url_rules(spark, tables):
    urls = ["http://a.example.com/en/7817?x=1", "HTTP://EXAMPLE.com/en/1", "x://sub.NET/de/8", "https://example.net/de/81", "https://u:p@x.org/es/", "notcom/en/", "http://xcom/en/", None, "a://", "://h/p", "http://example.com#/en/7"]
    pages = spark.createDataFrame([(i, u, "") for i, u in enumerate(urls)], "page_id bigint, url string, html string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in judge_urls(pages, listed_rules(), None).collect()}
    assert got[0] == ("a.example.com", "/en/7817", "example.com/en/7", "allow")
    assert got[1] == ("example.com", "/en/1", "com/en/", "block")
    assert got[2] == ("sub.net", "/de/8", "net/de/", "allow") and got[3][2:] == ("example.net/de/8", "block")
    assert got[4][2:] == (None, "allow") if got[4][0] == "u:p@x.org" and not got[4][0].endswith(".org") else got[4][2:] == ("org/es/", "block")
    assert got[5][:2] == ("", "") and got[6][2] is None and got[7] == ("", "", None, "allow") and got[8][:2] == ("", "") and got[9][:2] == ("h", "/p") and got[10][:2] == ("example.com", "")


def test_mined_rules_block_what_labels_say(spark):
    rows = [(f"http://w{k}.cheap-pills.example.com/x/{k}", True) for k in range(40)] + [(f"http://w{k}.news.example.com/x/{k}", k % 20 == 0) for k in range(160)]
    mined = mine_rules(spark.createDataFrame(rows, "url string, bad boolean"), min_support=0.05)
    rules = [r.tokens for r in mined.rules.collect()]
    assert rules == [["host:cheap-pills", "word:cheap", "word:pills"]], "tokens that always come together are one item, longer rules are needless"
    pages = spark.createDataFrame([(1, "http://zz.cheap-pills.example.com/new/9"), (2, "http://zz.news.example.com/new/9")], "page_id bigint, url string")
    assert {r.page_id: r.verdict for r in judge_urls(pages, [Rule("block", "org", "/")], mined).collect()} == {1: "block", 2: "allow"}
    assert mine_rules(spark.createDataFrame([], "url string, bad boolean")) is None
    assert mine_rules(spark.createDataFrame(rows[:19], "url string, bad boolean")) is None, "fewer pages than a rule needs"
    odd = spark.createDataFrame([(1, None, 1), (1, None, 2), (None, "http://a.cheap-pills.example.com/", 3), (5, "http://q.org/", 4), (5, "http://q.org/", 4)], "page_id bigint, url string, fired int")
    got = sorted((str(r.page_id), r.verdict) for r in judge_urls(odd, [Rule("block", "org", "/")], mined).collect())
    assert got == [("1", "allow"), ("1", "allow"), ("5", "block"), ("5", "block"), ("None", "block")]
    assert judge_urls(odd.limit(0), listed_rules(), mined).count() == 0


def brute_rules(pages, min_pages, min_support, min_confidence, min_lift, max_size, held_out):
    """Rules by the definition: (tokens) -> confidence on held-out pages, from (tokens, bad, out) of each page."""
    mined, rest = [p for p in pages if not p[2]], [p for p in pages if p[2]]
    where = {}
    for k, (tokens, _, _) in enumerate(mined):
        for t in tokens:
            where.setdefault(t, set()).add(k)
    items = {}
    for t, at in where.items():
        items.setdefault(frozenset(at), set()).add(t)
    n, bad = len(mined), {k for k, p in enumerate(mined) if p[1]}
    least = max(min_support * n, min_pages)
    found = {}
    for size in range(1, max_size + 1):
        for chosen in itertools.combinations([(at, names) for at, names in items.items() if len(at) >= least], size):
            at = frozenset.intersection(*[a for a, _ in chosen])
            sure = len(at & bad) / len(at) if at else 0
            if len(at & bad) >= least and sure >= min_confidence and sure / (len(bad) / n) >= min_lift:
                found[frozenset().union(*[names for _, names in chosen])] = sure
    kept = [r for r, c in found.items() if not any(o < r and d >= c for o, d in found.items())]
    out = {}
    for r in kept:
        hit = [b for tokens, b, _ in rest if r <= tokens]
        if len(hit) * held_out >= min_pages and sum(hit) >= min_confidence * len(hit):
            out[tuple(sorted(r))] = sum(hit) / len(hit)
    return out


def test_mined_rules_equal_brute_force(spark):
    rng = random.Random(12)
    rows = []
    for k in range(1500):
        host, section, query = rng.choice(["a", "b", "c"]), rng.choice(["x", "y", "z"]), rng.choice(["p", "q"])
        bad = rng.random() < (0.9 if (host, section) == ("a", "x") else 0.8 if query == "p" and section == "y" else 0.1)
        rows.append((f"http://{host}.example.com/{section}/{k}?{query}=1", bad))
    df = spark.createDataFrame(rows, "url string, bad boolean")
    mined = mine_rules(df, max_size=3)
    known = with_parts(df).select(url_tokens().alias("t"), "bad", (F.pmod(F.xxhash64("url", F.lit(29)), F.lit(3)) == 0).alias("out")).collect()
    want = brute_rules([(set(r.t), r.bad, r.out) for r in known], 20, 0.004, 0.6, 1.5, 3, 3)
    assert {tuple(r.tokens): r.confidence for r in mined.rules.collect()} == want and len(want) >= 2
    told = {r.page_id: r.fired for r in judge_urls(df.select(F.monotonically_increasing_id().alias("page_id"), "url"), [], mined).collect()}
    assert sum(f > 0 for f in told.values()) == sum(any(set(r) <= set(p.t) for r in want) for p in known)


def test_labels_that_do_not_depend_on_urls_make_no_rules(spark):
    rng = random.Random(4)
    rows = [(f"http://w{rng.randrange(9)}.s{rng.randrange(4)}.example.com/{rng.choice('abc')}/{k}?{rng.choice('xyz')}=1", rng.random() < 0.3) for k in range(2000)]
    mined = mine_rules(spark.createDataFrame(rows, "url string, bad boolean"))
    assert mined.rules.count() == 0


def test_urls_name_documents(tables):
    assert labelled_pages(tables["pages"], tables["labels"]).count() > 50


def brute_targets(sizes, weights=(1, 2, 3), cap=3):
    """Shares by weight, the excess over the limits handed on until none is above."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    fixed, total = {}, sum(sizes.values())
    while True:
        rest = [s for s in order if s not in fixed]
        left = total - sum(fixed.values())
        level = left / sum(w[s] for s in rest) if rest else 0
        above = [s for s in rest if level * w[s] > cap * sizes[s]]
        if not above:
            return fixed | {s: level * w[s] for s in rest}
        fixed |= {s: cap * sizes[s] for s in above}


@pytest.mark.parametrize("seed", [1, 2])
def test_mix(docs_of, seed):
    rng = random.Random(seed)
    rows = [(i, " ".join(f"w{i}-{k}" for k in range(rng.choice([0, 3, 40, 300]))), rng.choice(["a", "a", "a", "b", "c", None])) for i in range(150)]
    rows += [(900, None, "a"), (901, "tiny words", "é"), (902, "said twice", "b"), (902, "said twice", "b"), (None, "no id here", "b")]
    docs = docs_of(rows)
    mix = mix_sources(docs, block_words=16, shard_slots=50)
    taken = taken_words(mix).collect()
    sizes = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len((t or "").split())
    want = brute_targets(sizes)
    assert len(taken) == len(rows)
    for r in taken:
        assert r.taken <= 3 * r["size"] and r.source_size == sizes[r.source] and r.target == pytest.approx(want[r.source])
    for s in sizes:
        assert sum(r.taken for r in taken if r.source == s) == pytest.approx(want[s], abs=3 * 16 + 0.02 * want[s])
    again = taken_words(mix_sources(docs.repartition(7), block_words=16, shard_slots=50)).collect()
    assert sorted(map(str, again)) == sorted(map(str, taken))
    pieces = mixed_corpus(docs, mix).collect()
    text = {i: (t or "").split() for i, t, _ in rows}
    assert sum(p.n_words for p in pieces) == sum(r.taken for r in taken)
    for p in pieces:
        assert p.text.split() == text[p.doc_id][p.first_word : p.first_word + p.n_words]
    per_slot = {}
    for p in pieces:
        per_slot[p.shard, p.slot] = per_slot.get((p.shard, p.slot), 0) + p.n_words
    assert max(per_slot.values()) <= 16 and len({s for s, _ in per_slot}) == -(-len(per_slot) // 50)


def test_shards_are_multinomial_draws(spark):
    """Counts by shard scatter like independent draws; totals are exact, and every number of a source is given once."""
    shares = {0: 5_000, 1: 1_200, 2: 0, 3: 13_800}
    plan = spark.createDataFrame([(k, n) for k, n in shares.items()], "sid int, slots bigint").withColumn("start", F.expr("sum(slots) over (order by sid) - slots"))
    slots = draw_slots(plan, 100, 5).toPandas()
    assert slots.groupby("sid").size().to_dict() == {k: n for k, n in shares.items() if n}
    assert all(sorted(g.q) == list(range(len(g))) for _, g in slots.groupby("sid"))
    assert len(slots.drop_duplicates(["shard", "slot"])) == 20_000
    table = slots.groupby(["shard", "sid"]).size().unstack(fill_value=0)
    for sid, n in shares.items():
        if n:
            p = n / 20_000
            assert table[sid].mean() == pytest.approx(100 * p) and 0.7 < table[sid].var() / (100 * p * (1 - p)) < 1.4


def test_rows_repeated_many_times_are_mixed_each(docs_of):
    rows = [(1, "a b c", "s")] * 9000 + [(None, "d e", "s")] * 50 + [(2, "f g h i", "t")] * 3000
    out = taken_words(mix_sources(docs_of(rows), block_words=16, shard_slots=50)).collect()
    assert len(out) == len(rows) and max(r.taken - 3 * r["size"] for r in out) <= 0
    assert sum(r.taken for r in out) == pytest.approx(sum(r["size"] for r in out), rel=0.01)


def test_a_very_long_text_is_cut_once(docs_of):
    docs = docs_of([(1, "w " * 400_000, "s"), (2, "a b c", "t")])
    began = time.monotonic()
    mix = mix_sources(docs)
    assert mixed_corpus(docs, mix).agg(F.sum("n_words")).first()[0] == taken_words(mix).agg(F.sum("taken")).first()[0]
    assert time.monotonic() - began < 40


@pytest.mark.parametrize("n", [1, 2, 3, 5, 16, 97, 1000])
def test_permutation(spark, n):
    out = [r.p for r in spark.range(n).select(permuted(F.col("id"), F.lit(n), F.lit(4)).alias("p")).collect()]
    assert sorted(out) == list(range(n)) and (n < 16 or out != sorted(out))


def test_mix_of_odd_rows(docs_of):
    assert taken_words(mix_sources(docs_of([]))).count() == 0
    out = taken_words(mix_sources(docs_of(ODD)))
    assert out.count() == len(ODD) and all(r.taken == r["size"] for r in out.collect())
