"""Media columns: chroma audio fingerprints, searched and aligned.

A recording's samples become frames of pitch-class energy; filters over an
integral image of the frames give a packed 32-bit integer for each window of
frames.  Two recordings are aligned by the histogram of the offsets at which
they hold equal integers, and judged by the share of bits in which they differ
at the best offset.  Noise seldom leaves whole integers equal, so every searched
recording is also compared with all others by its bits alone, at every offset.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sparsegrid.plans.lineage import cut_lineage

RATE, FRAME, HOP = 4000, 1024, 512
BANDS, WIDTH = 12, 16


def _filters() -> list[tuple[int, int, int, int]]:
    """Sixteen filters (kind, first band, bands, frames), by a rule: every kind at several places and sizes."""
    return [(k % 4, (5 * k) % BANDS, 2 + (3 * k) % 5, (4, 8, 16)[k % 3]) for k in range(16)]


FILTERS = _filters()


def chroma_frames(samples: np.ndarray) -> np.ndarray:
    """Pitch-class frames (frames x 12) of mono samples, each scaled to length one."""
    n = (len(samples) - FRAME) // HOP + 1
    if n <= 0:
        return np.zeros((0, BANDS))
    frames = np.lib.stride_tricks.sliding_window_view(samples, FRAME)[::HOP][:n]
    power = np.abs(np.fft.rfft(frames * np.hanning(FRAME), axis=1)) ** 2
    hertz = np.fft.rfftfreq(FRAME, 1 / RATE)
    use = (hertz >= 100) & (hertz <= 1900)
    pitch = np.round(12 * np.log2(hertz[use] / 440.0)).astype(int) % BANDS
    out = np.zeros((n, BANDS))
    for b in range(BANDS):
        out[:, b] = power[:, use][:, pitch == b].sum(1)
    size = np.sqrt((out**2).sum(1, keepdims=True))
    return np.where(size > 1e-9, out / np.maximum(size, 1e-9), 0.0)


def fingerprint(frames: np.ndarray) -> np.ndarray:
    """A packed 32-bit integer for each window of WIDTH frames: two bits from each filter."""
    n = len(frames) - WIDTH + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    image = np.zeros((len(frames) + 1, 2 * BANDS + 1))
    image[1:, 1:] = np.cumsum(np.cumsum(np.hstack([frames, frames]), 0), 1)

    def area(x0: int, x1: int, y0: int, y1: int) -> np.ndarray:
        return image[x1 : x1 + n, y1] - image[x0 : x0 + n, y1] - image[x1 : x1 + n, y0] + image[x0 : x0 + n, y0]

    code = np.zeros(n, np.uint32)
    for kind, y, h, w in FILTERS:
        if kind == 0:  # all against nothing
            a, b = area(0, w, y, y + h), np.full(n, h * w / 4.0)
        elif kind == 1:  # upper against lower bands
            a, b = area(0, w, y, y + h // 2), area(0, w, y + h // 2, y + h)
        elif kind == 2:  # earlier against later frames
            a, b = area(0, w // 2, y, y + h), area(w // 2, w, y, y + h)
        else:  # opposite corners
            a = area(0, w // 2, y, y + h // 2) + area(w // 2, w, y + h // 2, y + h)
            b = area(w // 2, w, y, y + h // 2) + area(0, w // 2, y + h // 2, y + h)
        d = np.log1p(np.maximum(a, 0)) - np.log1p(np.maximum(b, 0))
        level = (d > -0.25).astype(np.uint32) + (d > 0) + (d > 0.25)
        code = (code << np.uint32(2)) | (level ^ (level >> np.uint32(1))).astype(np.uint32)
    return code


def melody(vector) -> np.ndarray:
    """Samples of a recording that plays a note for each component of a vector.

    The given tables hold no sound; this stands in for decoding a media column.
    Unknown components are zero; an unknown vector is silent for no time at all.
    """
    v = np.array([np.nan if x is None else x for x in (vector if vector is not None else [])], np.float64)
    v = np.where(np.isfinite(v), v, 0.0)
    size = np.sqrt((v**2).mean()) if len(v) else 0.0
    note = np.clip(np.round(6 * v / size if size > 0 else v), -18, 18)
    step = np.arange(HOP) / RATE
    return np.sin(2 * np.pi * (440.0 * 2 ** (note / 12))[:, None] * step[None, :]).ravel()


def decode_pcm(data: bytes | None) -> np.ndarray:
    """Samples of 16-bit little-endian mono sound, the form a binary media column holds; a half sample at the end is left out."""
    return np.frombuffer(data or b"", "<i2", len(data or b"") // 2).astype(np.float64) / 32768.0


def encode_pcm(samples: np.ndarray) -> bytes:
    return np.clip(np.round(samples * 32767), -32768, 32767).astype("<i2").tobytes()


def _printed(decode):
    def run(batches):
        for batch in batches:
            codes = [fingerprint(chroma_frames(decode(x.as_py()))).astype(np.int64) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(codes, pa.list_(pa.int64()))], ["media_id", "codes"])

    return run


def fingerprints(table: DataFrame, id_column: str, media_column: str, decode=decode_pcm) -> DataFrame:
    """(media_id, codes) of a media column; ``decode`` gives the samples of a value, one recording at a time.

    Null, empty and too short recordings have no codes.  A table in fewer
    partitions than the session's shuffles have is dealt out first: decoding
    costs far more than its bytes tell.
    """
    media = table.select(F.col(id_column).cast("long").alias("media_id"), media_column)
    tasks = int(table.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    media = media.repartition(tasks) if media.rdd.getNumPartitions() < tasks else media
    return media.mapInArrow(_printed(decode), "media_id long, codes array<long>")


def _popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x.astype(np.uint32))


def bit_errors(a: np.ndarray, b: np.ndarray, offset: int) -> tuple[int, int]:
    """(differing bits, compared codes) with a's code i at b's code i + offset."""
    lo, hi = max(0, -offset), min(len(a), len(b) - offset)
    if hi <= lo:
        return 0, 0
    return int(_popcount(a[lo:hi] ^ b[lo + offset : hi + offset]).sum()), hi - lo


def _runs(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of equal codes, ordered by code: (code, first, last)."""
    new = np.ones(len(codes), bool)
    new[1:] = codes[1:] != codes[:-1]
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(codes)) - 1
    order = np.argsort(codes[first], kind="stable")
    return codes[first][order], first[order], last[order]


def best_offset(x: np.ndarray, y: np.ndarray) -> tuple[int, int]:
    """(votes, offset): the offset at which most codes of y equal those of x, the smallest of equals.

    Two runs of one code agree at a stretch of offsets, in numbers that rise,
    stay and fall by one a step: four turning points, whatever their lengths.
    Votes are what the turning points of all runs add up to.  A code with very
    many runs on both sides is counted by a cross-correlation instead.
    """
    if not len(x) or not len(y):
        return 0, 0
    (cx, a1, a2), (cy, b1, b2) = _runs(x), _runs(y)
    shared = np.intersect1d(cx, cy)
    zero, size = len(x) - 1, len(x) + len(y)
    bends, votes = np.zeros(size + 3, np.int64), np.zeros(size + 3, np.int64)
    many = []
    for code in shared:
        i, j = slice(*np.searchsorted(cx, [code, code + 1])), slice(*np.searchsorted(cy, [code, code + 1]))
        if (i.stop - i.start) * (j.stop - j.start) > 8 * size:
            many.append(code)
            continue
        for at, w in ((b1[None, j] - a2[i, None], 1), (b1[None, j] - a1[i, None] + 1, -1), (b2[None, j] - a2[i, None] + 1, -1), (b2[None, j] - a1[i, None] + 2, 1)):
            np.add.at(bends, (at + zero).ravel(), w)
    votes += np.cumsum(np.cumsum(bends))
    for code in many:
        f = np.fft.rfft((x == code).astype(float)[::-1], size)
        votes[: size - 1] += np.rint(np.fft.irfft(f * np.fft.rfft((y == code).astype(float), size), size)).astype(np.int64)[: size - 1]
    best = int(votes.argmax())
    return (int(votes[best]), best - zero) if votes[best] else (0, 0)


def _aligned(batches):
    for batch in batches:
        told = []
        for a, b in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True):
            x, y = np.asarray(a, np.int64), np.asarray(b, np.int64)
            votes, offset = best_offset(x, y)
            told.append((offset, votes, *bit_errors(x.astype(np.uint32), y.astype(np.uint32), offset)))
        found = [pa.array([t[k] for t in told], pa.int64()) for k in range(4)]
        yield pa.RecordBatch.from_arrays([batch.column("query"), batch.column("match"), *found], ["query", "match", "offset", "votes", "bit_errors", "frames"])


def _spectra(block: list[np.ndarray], size: int) -> np.ndarray:
    """(frequencies, recordings, 32) transforms along time of the bits as signs; recordings are padded with zeros."""
    signs = np.zeros((len(block), max(map(len, block)), 32), np.float32 if size <= EXACT else np.float64)
    for k, codes in enumerate(block):
        signs[k, : len(codes)] = 1.0 - 2.0 * np.unpackbits(codes.astype("<u4").view(np.uint8).reshape(-1, 4), axis=1)
    return np.ascontiguousarray(np.fft.rfft(signs, size, axis=1).transpose(1, 0, 2))


EXACT = 4096  # up to this length sums of signs round to the right integer in single precision
_TILE = 1 << 21  # sums held at once


def close_pairs(xs: list[np.ndarray], ys: list[np.ndarray], max_error: float, min_frames: int) -> tuple[np.ndarray, ...]:
    """(x, y, offset, bit errors, frames) of the pairs that come within ``max_error`` over ``min_frames`` codes or more.

    The offset is that of the least share of errors, the smallest of equals.
    Agreements less differences of bits at all offsets are one cross-correlation
    of signs, a matrix product for each frequency; its values are integers, so
    rounding makes them exact.
    """
    out = [np.zeros((5, 0), np.int64)]
    n_x, n_y = (np.array([len(c) for c in block], np.int64) for block in (xs, ys))
    long_x, long_y = int(n_x.max(initial=0)), int(n_y.max(initial=0))
    least = max(min_frames, 1)
    offsets = np.arange(least - long_x, long_y - least + 1)
    if min(long_x, long_y) < least:
        return tuple(out[0])
    size = long_x + long_y - least
    size += size % 2
    step_x = max(1, min(64, _TILE // size))
    step_y = max(1, _TILE // size // step_x)
    for b in range(0, len(ys), step_y):
        right = _spectra(ys[b : b + step_y], size).transpose(0, 2, 1)
        for a in range(0, len(xs), step_x):
            left = np.conj(_spectra(xs[a : a + step_x], size))
            sums = np.fft.irfft(left @ right, size, axis=0)[offsets % size]
            # equal lengths need one count of frames for each offset
            p, q = n_x[a : a + step_x, None], n_y[None, b : b + step_y]
            p, q = (v[:1, :1] if (v == v[0, 0]).all() else v for v in (p, q))
            at = offsets[:, None, None]
            frames = np.minimum(p, q - at) - np.maximum(0, -at)
            enough = np.where(frames >= least, 32 * frames * (1 - 2 * max_error) - 0.5, np.inf).astype(sums.dtype)
            i, j = np.nonzero((sums >= enough).any(0))
            whole = np.rint(sums[:, i, j]).astype(np.int64)
            frames = np.broadcast_to(frames, sums.shape)[:, i, j]
            errors = (32 * frames - whole) // 2
            fits = (frames >= least) & (errors <= max_error * 32 * frames)
            best = np.where(fits, errors / np.maximum(frames, 1), np.inf).argmin(0)
            k = np.arange(len(i))
            out.append(np.stack([i + a, j + b, offsets[best], errors[best, k], frames[best, k]])[:, fits.any(0)])
    return tuple(np.concatenate(out, 1))


def _compared(max_error: float, min_frames: int):
    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                ids, codes = [], []
                for side in ("asked", "others"):
                    block = batch.column(side)[row].values
                    flat, ends = block.field("codes"), block.field("codes").offsets.to_numpy()
                    ids.append(block.field("id").to_numpy())
                    values = flat.values.to_numpy().astype(np.uint32)
                    codes.append([values[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)])
                x, y, *rest = close_pairs(*codes, max_error, min_frames)
                query, match = ids[0][x], ids[1][y]
                order = np.lexsort((match, query))
                order = order[query[order] != match[order]]
                names, first = np.unique(query[order], return_index=True)
                found = pa.StructArray.from_arrays([pa.array(v[order]) for v in (match, *rest)], ["match", "offset", "bit_errors", "frames"])
                lists = pa.ListArray.from_arrays(pa.array([*first, len(order)], pa.int32()), found)
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), lists], ["query", "part"])

    return run


def _close(held: DataFrame, max_error: float, min_frames: int, codes_asked: int = 1 << 14, codes_other: int = 1 << 17) -> DataFrame:
    """(query, close) of the asked classes against all of ``held``, block by block: every pair is compared."""
    total = held.agg(F.sum(F.size("codes")), F.sum(F.when(F.col("asked"), F.size("codes")))).first()

    def blocks(rows: DataFrame, codes: int, most: int, name: str) -> DataFrame:
        dealt = rows.withColumn("block", F.pmod(F.xxhash64("class_id", F.lit(name)), F.lit(-(-codes // most) or 1)))
        return dealt.groupBy("block").agg(F.collect_list(F.struct(F.col("class_id").alias("id"), "codes")).alias(name)).select(name)

    pairs = blocks(held, total[0] or 0, codes_other, "others").crossJoin(blocks(held.where("asked"), total[1] or 0, codes_asked, "asked"))
    parts = pairs.mapInArrow(_compared(max_error, min_frames), "query long, part array<struct<match:long,offset:long,bit_errors:long,frames:long>>")
    return parts.groupBy("query").agg(F.array_sort(F.flatten(F.collect_list("part"))).alias("close"))


def _sharing(held: DataFrame, min_votes: int, per_task: int = 4096) -> DataFrame:
    """(query, match): asked classes and others with enough codes in common to have ``min_votes`` equal ones at one offset.

    One row for each distinct code that two recordings share, however often they
    hold it: no offset has more equal codes than the smaller of both counts
    add up to.  A code that many recordings hold is split by salt.
    """
    counts = cut_lineage(held.select("class_id", "asked", F.explode("codes").alias("code")).groupBy("class_id", "asked", "code").agg(F.count("*").alias("n")))
    asked = counts.where("asked").groupBy("code").agg(F.count("*").alias("k")).select("code")
    salts = cut_lineage(counts.groupBy("code").agg(F.ceil(F.count("*") / per_task).alias("salts")).join(asked, "code"))
    index = counts.join(salts, "code").withColumn("salt", F.pmod(F.xxhash64("class_id"), F.col("salts")))
    asking = counts.where("asked").join(salts, "code").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1)))
    met = asking.alias("q").join(index.alias("r"), ["code", "salt"]).where("q.class_id <> r.class_id")
    most = met.groupBy(F.col("q.class_id").alias("query"), F.col("r.class_id").alias("match")).agg(F.sum(F.least("q.n", "r.n")).alias("most"))
    return most.where(F.col("most") >= min_votes).select("query", "match")


def search_recordings(prints: DataFrame, query_step: int = 20, min_votes: int = 3, max_error: float = 0.3, min_frames: int = 16) -> DataFrame:
    """One row per row of ``prints`` (media_id, codes): media_id, class_id, n_codes, is_query, matches, close.

    Equal fingerprints form a class, named by its smallest id.  Rows whose id is
    divisible by ``query_step`` are searched for among all: ``matches`` lists
    the other classes with at least ``min_votes`` equal codes at one offset, at
    least ``min_frames`` compared codes there and at most ``max_error`` of the
    bits different at the offset with most votes (the smallest of equals).  All
    such classes are found: codes meet by an exact join, without caps.  ``close``
    lists all other classes that come within ``max_error`` over ``min_frames``
    codes or more, whether codes are equal or not, at the offset of the least
    share of errors; every searched class is compared with every class, so this
    costs searched times all.  Rows without codes have no class, no matches and
    nothing close; a null id is no query; of the sounds that
    share a smallest id the one with the smallest hash is searched and found for
    all; other columns are ignored; an empty table gives no rows.
    """
    prints = cut_lineage(prints.select("media_id", F.coalesce("codes", F.array().cast("array<long>")).alias("codes")).withColumn("print", F.xxhash64("codes")).withColumn("print2", F.xxhash64(F.lit("print"), "codes")))
    is_query = F.coalesce(F.col("media_id") % query_step == 0, F.lit(False))
    some = prints.where("size(codes) > 0 AND media_id IS NOT NULL")
    classes = some.groupBy("print", "print2").agg(F.min("media_id").alias("class_id"), F.max(is_query).alias("asked"))
    held = some.join(classes, ["print", "print2"]).where("media_id = class_id").groupBy("class_id").agg(F.min(F.struct("print", "print2", "codes", "asked")).alias("m"))
    held = cut_lineage(held.select("class_id", "m.codes", "m.asked"))
    sharing = _sharing(held, min_votes)
    pairs = sharing.join(held.select(F.col("class_id").alias("query"), F.col("codes").alias("x")), "query").join(held.select(F.col("class_id").alias("match"), F.col("codes").alias("y")), "match")
    judged = pairs.select("query", "match", "x", "y").mapInArrow(_aligned, "query long, match long, offset long, votes long, bit_errors long, frames long").where(F.col("votes") >= min_votes)
    good = judged.where((F.col("frames") >= min_frames) & (F.col("bit_errors") <= max_error * 32 * F.col("frames")))
    lists = good.groupBy("query").agg(F.array_sort(F.collect_list(F.struct("match", "offset", "votes", "bit_errors", "frames"))).alias("found"))
    out = prints.join(classes.select("print", "print2", "class_id"), ["print", "print2"], "left").withColumn("is_query", is_query)
    out = out.join(lists, (F.col("class_id") == F.col("query")) & F.col("is_query"), "left")
    near = _close(held, max_error, min_frames).withColumnRenamed("query", "near")
    out = out.join(near, (F.col("class_id") == F.col("near")) & F.col("is_query"), "left")

    def none(*names: str):
        return F.array().cast(T.ArrayType(T.StructType([T.StructField(c, T.LongType()) for c in names])))

    matches = F.coalesce("found", none("match", "offset", "votes", "bit_errors", "frames")).alias("matches")
    close = F.coalesce("close", none("match", "offset", "bit_errors", "frames")).alias("close")
    return out.select("media_id", F.when(F.col("media_id").isNotNull(), F.col("class_id")).alias("class_id"), F.size("codes").cast("long").alias("n_codes"), "is_query", matches, close)
