"""Personal data: fixed patterns, and a semi-Markov conditional random field.

The patterns give the base spans.  Around signs of personal data (digits, ``@``,
a quoted word after ``=``, a spelled-out mail) the random field reads a stretch of tokens and
scores whole candidate segments by features of the entire span: its shape, its
digits, its check sum, what stands before and after.  Dynamic programming over
segments of bounded length chooses boundaries and kinds together.  Its spans are
added where they touch no base span.

The field is trained here, in numpy, on generated stretches: neutral words,
dates, prices and versions, and personal data in the forms people write it.
"""

from __future__ import annotations

import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "secret")
OUT = len(KINDS)  # the kind of a token that is no entity
LONGEST = 16  # tokens of an entity

# The base patterns.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def luhn(digits: str) -> bool:
    """The check sum of card numbers."""
    odd = sum(int(d) for d in digits[-1::-2])
    even = sum(int(d) // 5 + 2 * int(d) % 10 for d in digits[-2::-2])
    return (odd + even) % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches: from each ``@`` as far back as the local part goes, in linear time."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
        done = m.end() if m else at + 1
        at = text.find("@", max(done, at + 1))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind, start, end) of the base patterns, by kind and then start; code points."""
    out = [(0, a, b) for a, b in _emails(text)] if "@" in text else []
    out += [(1, m.start(), m.end()) for m in _IP.finditer(text) if all(len(p) <= 3 and int(p) <= 255 for p in (x.lstrip("0") or "0" for x in m[0].split(".")))]
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 13 <= len(digits) <= 19 and luhn(digits):
            out.append((2, m.start(), m.end()))
    if "+" in text:
        out += [(3, m.start(), m.end()) for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return out


_TOKEN = re.compile(r"[^\W_]+|[ \t]+|\n|.", re.S)
_DIGIT = re.compile("[0-9]")
_TRIGGER = re.compile(r"[0-9]{2,}|@|=[ \t]*[\"']|\bat[ \t]+[^\W_]+[ \t]+dot[ \t]", re.I)
_ENDINGS = frozenset("com org net edu gov info io de fr es uk eu".split())  # of spelled-out mails without digits
BEFORE, AFTER = 40, 44  # characters read around a sign, and LONGEST tokens at least
PIECE = 2000  # characters decoded at once
_SETTLED = 3 * LONGEST  # tokens that must follow for a boundary to stand


@dataclass
class Stretch:
    """Tokens of a part of a text with their places."""

    words: list[str]
    start: list[int]
    end: list[int]


def _back(text: str, at: int, floor: int) -> int:
    """Where the BEFORE characters and LONGEST tokens before ``at`` begin, not before ``floor``; a token is taken whole."""
    start, tokens = at, 0
    while at > floor and (start - at < BEFORE or tokens < LONGEST):
        at -= 1
        if text[at].isalnum():
            while at > floor and text[at - 1].isalnum():
                at -= 1
        elif text[at] in " \t":
            while at > floor and text[at - 1] in " \t":
                at -= 1
        tokens += 1
    return at


def _ahead(text: str, at: int) -> int:
    """Where the AFTER characters and LONGEST tokens from ``at`` end; a token is taken whole."""
    end = at
    for k, t in enumerate(_TOKEN.finditer(text, at)):
        if k >= LONGEST and end - at >= AFTER:
            break
        end = t.end()
    return end


def stretches(text: str) -> Iterator[tuple[int, int]]:
    """(start, end) of the parts of a text that hold signs of personal data, with some context.

    Parts end between tokens; signs whose surroundings touch belong to one part,
    however long, so an entity with a sign lies in one part as a whole.
    """
    lo, last, reach = -1, 0, 0
    for m in _TRIGGER.finditer(text):
        if lo >= 0 and m.start() - last > AFTER:
            reach = _ahead(text, last)
            if m.start() > reach and (start := _back(text, m.start(), reach)) > reach:
                yield lo, reach
                lo = start
        elif lo < 0:
            lo = _back(text, m.start(), 0)
        last = m.end()
    if lo >= 0:
        yield lo, _ahead(text, last)


def decode_part(text: str, lo: int, hi: int, model: SegmentField) -> Iterator[tuple[int, int, int]]:
    """Entities of one part, read in pieces that overlap.

    A piece stands up to its last boundary that _SETTLED tokens follow; the next
    piece goes on there, and sees the tokens before.
    """
    begin, size, kind = lo, PIECE, OUT
    seen = lo  # where the tokens begin that are shown before
    while begin < hi:
        end = min(hi, begin + size)
        found = list(_TOKEN.finditer(text, seen, end))
        s = Stretch([t[0] for t in found], [t.start() for t in found], [t.end() for t in found])
        first = next(k for k, t in enumerate(s.start) if t >= begin)
        settled = len(s.words) if end == hi else len(s.words) - _SETTLED
        if settled <= first:
            size *= 2  # a few very long tokens
            continue
        segments = model.segments(s, first, kind)
        stand = [x for x in segments if x[2] <= settled]
        if not stand:
            size *= 2
            continue
        while end < hi and len(stand) > 1 and stand[-1][0] != OUT:
            stand.pop()
        for y, i, j in stand:
            if y != OUT:
                yield y, s.start[i], s.end[j - 1]
        kind, _, j = stand[-1]
        begin, seen, size = s.end[j - 1], s.start[max(0, j - 3)], PIECE


def _shape(s: str) -> str:
    s = re.sub(r"[0-9]+", "9", s)
    s = re.sub(r"[^\W\d_]+", "a", s)
    return re.sub(r"(?:9a|a9)[9a]*", "x", s)[:24]


@dataclass
class Spans:
    """Candidate segments of a stretch: first token, one past the last, feature names."""

    first: list[int]
    last: list[int]
    names: list[list[str]]


def candidates(s: Stretch, begin: int = 0) -> Spans:
    """Single tokens, and segments up to LONGEST tokens on one line that begin and end on a sign, digit or letter and hold a digit or a spelled-out mail."""
    first, last, names = [], [], []
    n = len(s.words)
    for i in range(begin, n):
        w = s.words[i]
        first.append(i)
        last.append(i + 1)
        names.append(_features(s, i, i + 1))
        if w.isspace() or not (w[0].isalnum() or w in "+(\"'"):
            continue
        digit = at = dot = False
        for j in range(i + 1, min(n, i + LONGEST) + 1):
            t = s.words[j - 1]
            if t == "\n":
                break
            at = at or (j > i + 1 and t.lower() == "at")
            dot = dot or (at and t.lower() == "dot")
            digit = digit or _DIGIT.search(t) is not None
            if j > i + 1 and (digit or (dot and t.lower() in _ENDINGS)) and (t[-1].isalnum() or t in ")\"'"):
                first.append(i)
                last.append(j)
                names.append(_features(s, i, j))
    return Spans(first, last, names)


def _features(s: Stretch, i: int, j: int) -> list[str]:
    text = "".join(s.words[i:j])
    digits = [c for c in text if "0" <= c <= "9"]
    before = next((w for w in reversed(s.words[max(0, i - 3) : i]) if not w.isspace()), "^").lower()
    after = s.words[j] if j < len(s.words) else "$"
    out = ["bias", f"len={min(j - i, 12)}", "shape=" + _shape(text), f"digits={min(len(digits), 20)}", f"before={before[:12]}", f"glued={i > 0 and s.words[i - 1].isalnum()},{after.isalnum()}"]
    if "." in text and len(text) <= 15 and not text.strip("0123456789."):
        parts = text.split(".")
        out.append(f"ip={len(parts) == 4 and all(p and int(p) <= 255 for p in parts)}")
    if 12 <= len(digits) <= 19 and not text.strip("0123456789 -"):
        out.append(f"luhn={luhn(''.join(digits))}")
    if "@" in text or " at " in text:
        out.append("at,dot" if "." in text or " dot " in text else "at")
    if len(text) >= 16 and " " not in text:
        core = text.strip("\"'")
        letters = sum(c.isalpha() for c in core)
        out.append(f"mixed={bool(digits) and letters > 3},{len(core) >= 20},{core.isalnum()}")
    return out


@dataclass
class SegmentField:
    """Weights of span features for each kind, and of neighbouring kinds."""

    index: dict[str, int] = field(default_factory=dict)
    weight: np.ndarray = field(default_factory=lambda: np.zeros((0, OUT + 1)))
    follow: np.ndarray = field(default_factory=lambda: np.zeros((OUT + 1, OUT + 1)))

    def scores(self, spans: Spans) -> np.ndarray:
        """Scores of every candidate for every kind; longer ones cannot be OUT."""
        out = np.zeros((len(spans.first), OUT + 1))
        for k, names in enumerate(spans.names):
            at = [self.index[x] for x in names if x in self.index]
            if at:
                out[k] = self.weight[at].sum(0)
        long = np.array(spans.last) - np.array(spans.first) > 1
        out[long, OUT] = -np.inf
        return out

    def segments(self, s: Stretch, begin: int = 0, kind: int = OUT) -> list[tuple[int, int, int]]:
        """The best segmentation (kind, first token, one past the last) from token ``begin`` on, where ``kind`` ends."""
        spans = candidates(s, begin)
        score = self.scores(spans)
        n = len(s.words)
        best = np.full((n + 1, OUT + 1), -np.inf)
        best[begin, kind] = 0.0
        back: dict[tuple[int, int], tuple[int, int]] = {}
        order = sorted(range(len(spans.first)), key=lambda k: spans.first[k])
        for k in order:
            i, j = spans.first[k], spans.last[k]
            via = best[i][:, None] + self.follow
            total = via.max(0) + score[k]
            better = total > best[j]
            if better.any():
                came = via.argmax(0)
                for y in np.flatnonzero(better):
                    best[j, y] = total[y]
                    back[j, int(y)] = (i, int(came[y]))
        out, j, y = [], n, int(best[n].argmax())
        while j > begin:
            i, x = back[j, y]
            out.append((y, i, j))
            j, y = i, x
        return out[::-1]


def _examples(count: int, seed: int) -> Iterator[tuple[str, list[tuple[int, int, int]]]]:
    """Generated stretches with their entities."""
    rng = random.Random(seed)
    digits = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    word = lambda: "".join(rng.choice("aeioubcdlmnrstvw") for _ in range(rng.randint(2, 9)))

    def card() -> str:
        body = rng.choice("3456789") + digits(14)
        body += next(d for d in "0123456789" if luhn(body + d))
        sep = rng.choice(["", "", "", " ", "-"])
        return sep.join(body[k : k + 4] for k in range(0, 16, 4))

    def entity() -> tuple[int, str]:
        kind = rng.randrange(len(KINDS))
        if kind == 0:
            name, host = word() + rng.choice(["", ".", "_"]) + digits(rng.randint(0, 3)), word() + rng.choice(["", digits(1)])
            if rng.random() < 0.7:
                return 0, f"{name}{rng.choice(['', word()])}@{host}.{rng.choice(['com', 'org', 'example.com', 'net'])}"
            return 0, f"{word()}{digits(rng.choice([0, 2, 2]))} at {host} dot {rng.choice(['com', 'org', 'net'])}"
        if kind == 1:
            return 1, ".".join(str(rng.randint(0, 255)) for _ in range(4))
        if kind == 2:
            return 2, card()
        if kind == 3:
            a, b, c = digits(3), digits(3), digits(4)
            return 3, rng.choice([f"+{digits(1)} ({a}) {b}-{c}", f"+{digits(2)} {a} {b} {c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"+{digits(11)}"])
        quote = rng.choice(['"', "'"])
        return 4, f"{quote}{''.join(rng.choice('0123456789abcdef') for _ in range(rng.choice([32, 40])))}{quote}"

    def neutral() -> str:
        return rng.choice([
            f"{rng.randint(1, 28)}.{rng.randint(1, 12)}.{rng.randint(1990, 2030)}", f"{rng.randint(1990, 2030)}-0{rng.randint(1, 9)}-{rng.randint(10, 28)}", f"Version {rng.randint(1, 9)}.{rng.randint(0, 20)}.",
            f"{rng.randint(1, 9)}.{rng.randint(0, 9)}.{rng.randint(0, 99)}", f"${rng.randint(1, 999)}.{digits(2)}", f"{rng.randint(10, 23)}:{digits(2)}", digits(rng.randint(2, 8)), f"{digits(2)} %", digits(16), digits(rng.choice([12, 20, 24])),
            f"{rng.randint(256, 999)}.{rng.randint(256, 999)}.{rng.randint(0, 99)}.1", f'x = "{word()}{digits(2)}"', f"{digits(3)} {word()} {digits(3)}", f"p. {digits(3)}-{digits(3)}",
        ])

    for _ in range(count):
        text, spans = "", []
        for _ in range(rng.randint(1, 3)):
            text += "".join(word() + rng.choice([" ", " ", ", ", ". "]) for _ in range(rng.randint(1, 4)))
            if rng.random() < 0.6:
                kind, body = entity()
                text += rng.choice(["token = ", "key = ", "secret: "]) if kind == 4 else ""
                spans.append((kind, len(text), len(text) + len(body)))
                text += body + rng.choice([" ", " ", ", ", ". ", "!! ", " | "])
                if kind == 2 and rng.random() < 0.3:
                    body = card()
                    text = text.rstrip("., !|") + " "
                    spans[-1] = (2, spans[-1][1], len(text) - 1)
                    spans.append((2, len(text), len(text) + len(body)))
                    text += body + " "
            else:
                text += neutral() + rng.choice([" ", ", ", "!! "])
        yield text + word(), spans


def train_field(count: int = 700, epochs: int = 6, rate: float = 0.3, seed: int = 3) -> SegmentField:
    """Maximum likelihood over all segmentations (forward and backward sums), adaptive gradients."""
    data = []
    index: dict[str, int] = {}
    for text, gold in _examples(count, seed):
        s = Stretch(*map(list, zip(*[(t[0], t.start(), t.end()) for t in _TOKEN.finditer(text)], strict=True)))
        spans = candidates(s)
        place = {(s.start[i], s.end[j - 1]): k for k, (i, j) in enumerate(zip(spans.first, spans.last, strict=True))}
        if any((a, b) not in place for _, a, b in gold):
            continue
        inside = {t for _, a, b in gold for t in range(len(s.words)) if a <= s.start[t] < b}
        chosen = sorted([(place[a, b], y) for y, a, b in gold] + [(place[s.start[t], s.end[t]], OUT) for t in range(len(s.words)) if t not in inside], key=lambda c: spans.first[c[0]])
        at = [np.array([index.setdefault(x, len(index)) for x in names]) for names in spans.names]
        data.append((spans, at, chosen, len(s.words)))
    model = SegmentField(index, np.zeros((len(index), OUT + 1)), np.zeros((OUT + 1, OUT + 1)))
    sq_w, sq_f = np.full_like(model.weight, 1e-2), np.full_like(model.follow, 1e-2)
    for _ in range(epochs):
        for spans, at, chosen, n in data:
            flat, owner = np.concatenate(at), np.repeat(np.arange(len(at)), [len(a) for a in at])
            score = np.stack([np.bincount(owner, model.weight[flat, y], len(at)) for y in range(OUT + 1)], 1)
            first, last = np.array(spans.first), np.array(spans.last)
            score[last - first > 1, OUT] = -1e9
            marg, pair = _expected(first, last, score, model.follow, n)
            for k, y in chosen:
                marg[k, y] -= 1
            previous = OUT
            for _, y in chosen:
                pair[previous, y] -= 1
                previous = y
            used, back = np.unique(flat, return_inverse=True)
            grad = np.stack([np.bincount(back, marg[owner, y], len(used)) for y in range(OUT + 1)], 1) + 1e-4 * model.weight[used]
            sq_w[used] += grad**2
            model.weight[used] -= rate * grad / np.sqrt(sq_w[used])
            sq_f += pair**2
            model.follow -= rate * pair / np.sqrt(sq_f)
    return model


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis)
    return top + np.log(np.exp(x - np.expand_dims(top, axis)).sum(axis))


def _expected(first: np.ndarray, last: np.ndarray, score: np.ndarray, follow: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Marginals of candidates by kind, and expected neighbouring kinds."""
    ends = [np.flatnonzero(last == j) for j in range(n + 1)]
    starts = [np.flatnonzero(first == i) for i in range(n + 1)]
    ahead = np.full((n + 1, OUT + 1), -1e9)
    ahead[0, OUT] = 0.0
    enter = np.full((n + 1, OUT + 1), -1e9)
    enter[0] = follow[OUT]
    for j in range(1, n + 1):
        if len(ends[j]):
            ahead[j] = _lse(enter[first[ends[j]]] + score[ends[j]], 0)
        enter[j] = _lse(ahead[j][:, None] + follow, 0)
    behind = np.full((n + 1, OUT + 1), -1e9)
    behind[n] = 0.0
    leave = np.full((n + 1, OUT + 1), -1e9)
    for i in range(n - 1, -1, -1):
        if len(starts[i]):
            leave[i] = _lse(score[starts[i]] + behind[last[starts[i]]], 0)  # best continuation by kind of the next segment
        behind[i] = _lse(follow + leave[i][None, :], 1)
    total = float(_lse(ahead[n], 0))
    marg = np.exp(np.minimum(enter[first] + score + behind[last] - total, 0.0))
    pair = np.zeros_like(follow)
    for i in range(n):
        pair += np.exp(np.minimum(ahead[i][:, None] + follow + leave[i][None, :] - total, 0.0))
    return marg, pair


_SIGNS = re.compile(r"[0-9@]|=[ \t]*[\"']|\bat[ \t]+[^\W_]+[ \t]+dot[ \t]", re.I)


def all_spans(text: str | None, model: SegmentField) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(base spans, added spans) of a whole text."""
    if not text or not _SIGNS.search(text):
        return [], []
    base = base_spans(text)
    taken = sorted((a, b) for _, a, b in base)
    starts = np.array([a for a, _ in taken])
    reach = np.maximum.accumulate(np.array([b for _, b in taken])) if taken else starts
    added = []
    for lo, hi in stretches(text):
        for y, a, b in decode_part(text, lo, hi, model):
            k = int(np.searchsorted(starts, b)) if taken else 0
            if k == 0 or reach[k - 1] <= a:
                added.append((y, a, b))
    return base, added


def _found(shared):
    def run(batches):
        model: SegmentField = shared.value
        for batch in batches:
            out = [all_spans(t.as_py(), model) for t in batch.column(1)]
            rows = [[[{"kind": KINDS[y], "start": a, "end": b} for y, a, b in spans] for spans in both] for both in out]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r[0] for r in rows], _SPANS), pa.array([r[1] for r in rows], _SPANS)], ["doc_id", "base", "added"])

    return run


_SPANS = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
_SPAN_DDL = "array<struct<kind:string,start:long,end:long>>"


def find_personal(docs: DataFrame, model: SegmentField) -> DataFrame:
    """(doc_id, base, added) for every row of ``docs``: spans in code points, ends exclusive.

    Null and empty texts have none; rows with a null id keep it; repeated rows
    are searched each; other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_found(shared), f"doc_id long, base {_SPAN_DDL}, added {_SPAN_DDL}")
