"""Media columns (operator 7): chroma audio fingerprints and their alignment.

1. A recording (WAV bytes) becomes frames of twelve pitch-class energies (:func:`chroma`).
2. Over the integral image of the frames, whose pitch axis wraps around, each of sixteen
   rectangle filters compares two areas in four sums or fewer; the logarithm of their ratio
   falls into one of four levels, Gray-coded in two bits. Sixteen filters pack into one
   32-bit integer a frame (:func:`codes`).
3. Two recordings are aligned by the histogram of the offsets at which they hold equal
   integers. The offset with the most votes counts if it has :data:`MIN_VOTES`, the
   recordings overlap there by :data:`MIN_OVERLAP` frames, and at most
   :data:`MAX_ERROR` of the overlap's bits differ (:func:`align`).

:func:`search` aligns a stated set of queries with all recordings. Recordings with equal
integers are one class and are compared once. The queries are dealt into blocks of a bounded
number of integers; one block at a time is sent to all tasks, and a task gives one summary a
query, never its pairs, so that a third of all recordings may be alike.

Defined results: null, malformed and too short recordings (fewer frames than the widest
filter) have no integers and match nothing; frames without any energy cast no votes; of
offsets with equal votes the one with fewer bit errors counts, then the smaller; of matches
the one with the smaller share of wrong bits, then the longer overlap, then the smaller id
is the best. Repeated rows and ids are recordings of their own. Empty tables give empty
results; other columns are carried by :func:`fingerprint` unless they clash with its own.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Callable
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import scratch, stepwise

#: Samples a second that frames are made from; samples of a frame and between frames.
RATE, WINDOW, HOP = 8000, 2048, 512
#: Weights of a frame and its two neighbours on either side.
BLEND = (0.25, 0.75, 1.0, 0.75, 0.25)
#: Frequencies that count towards pitch classes.
LOW_HZ, HIGH_HZ = 120.0, 3500.0
FILTERS, WIDEST = 16, 16
#: Bounds of the four levels of a filter's log ratio are minus this, zero and this.
LEVEL = 0.35
MIN_VOTES, MIN_OVERLAP, MAX_ERROR = 3, 16, 0.25
#: Integers of all queries that are sent to the tasks at once; pairs of equal integers held at once.
BLOCK_CODES, STEP_PAIRS = 1 << 20, 1 << 20


def read_wav(data: bytes | None) -> np.ndarray | None:
    """Mono samples at :data:`RATE` of a WAV file with PCM or float samples; None if malformed."""
    if not data or len(data) < 12 or data[:4] != b"RIFF" or data[8:12] != b"WAVE":
        return None
    at, form, body = 12, None, None
    while at + 8 <= len(data):
        name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
        if name == b"fmt " and size >= 16 and at + 24 <= len(data):
            form = struct.unpack_from("<HHIIHH", data, at + 8)
        elif name == b"data":
            body = data[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    if form is None or body is None:
        return None
    kind, channels, rate, _, align_, bits = form
    if kind == 0xFFFE:  # extensible: the sample width tells
        kind = 3 if bits == 64 else 1
    if not channels or not rate or align_ != channels * bits // 8 or not align_:
        return None
    body = body[: len(body) // align_ * align_]
    if kind == 3 and bits in (32, 64):
        x = np.frombuffer(body, f"<f{bits // 8}").astype(np.float32)
    elif kind == 1 and bits == 8:
        x = (np.frombuffer(body, np.uint8).astype(np.float32) - 128) / 128
    elif kind == 1 and bits in (16, 32):
        x = np.frombuffer(body, f"<i{bits // 8}").astype(np.float32) / np.float32(1 << bits - 1)
    elif kind == 1 and bits == 24:
        b = np.frombuffer(body, np.uint8).reshape(-1, 3).astype(np.int32)
        x = ((b[:, 0] << 8 | b[:, 1] << 16 | b[:, 2] << 24) >> 8).astype(np.float32) / np.float32(1 << 23)
    else:
        return None
    x = np.nan_to_num(x.reshape(-1, channels).mean(axis=1), posinf=0.0, neginf=0.0)
    return x if rate == RATE else _resample(x, rate)


def _resample(x: np.ndarray, rate: int) -> np.ndarray:
    """Samples at :data:`RATE`: a moving mean against folding, then linear interpolation."""
    if not len(x):
        return x
    wide = max(1, rate // RATE)
    if wide > 1:
        x = np.convolve(x, np.full(wide, 1 / wide, np.float32), "same")
    n = max(1, int(len(x) * RATE / rate))
    return np.interp(np.arange(n) * (rate / RATE), np.arange(len(x)), x).astype(np.float32)


def write_wav(samples: np.ndarray, rate: int = RATE) -> bytes:
    """A 16-bit mono WAV file."""
    body = (np.clip(samples, -1, 1) * 32767).astype("<i2").tobytes()
    return b"RIFF" + struct.pack("<I", 36 + len(body)) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, rate, 2 * rate, 2, 16) + b"data" + struct.pack("<I", len(body)) + body


def _folding() -> np.ndarray:
    """Bins of the spectrum by pitch classes: 1 where a bin belongs to a class."""
    hz = np.arange(WINDOW // 2 + 1) * (RATE / WINDOW)
    used = (hz >= LOW_HZ) & (hz <= HIGH_HZ)
    tone = np.round(12 * np.log2(np.where(used, hz, 440.0) / 440.0)).astype(int) % 12
    out = np.zeros((len(hz), 12), np.float32)
    out[np.flatnonzero(used), tone[used]] = 1
    return out


_fold = _folding()
_taper = np.hanning(WINDOW).astype(np.float32)


def chroma(samples: np.ndarray, step: int = 2048) -> np.ndarray:
    """Frames x 12 pitch-class energies, each frame of length one (all zero where silent)."""
    n = (len(samples) - WINDOW) // HOP + 1
    if n <= 0:
        return np.zeros((0, 12), np.float32)
    frames = np.lib.stride_tricks.sliding_window_view(samples, WINDOW)[::HOP]
    out = np.empty((n, 12), np.float32)
    for at in range(0, n, step):
        spectrum = np.fft.rfft(frames[at : at + step] * _taper, axis=1)
        out[at : at + step] = (spectrum.real**2 + spectrum.imag**2).astype(np.float32) @ _fold
    # Neighbouring frames are blended, so that a shift by less than a frame changes little.
    wide = np.pad(out, ((2, 2), (0, 0)), "edge")
    out = sum(w * wide[k : k + n] for k, w in enumerate(BLEND))
    size = np.linalg.norm(out, axis=1, keepdims=True)
    return np.where(size > 1e-6, out / np.maximum(size, 1e-6), 0).astype(np.float32)


def filters(n: int = FILTERS) -> list[tuple[int, int, int, int]]:
    """(kind, first pitch class, pitch classes, frames) of each filter, by rule.

    Kinds: 0 lower against upper pitches, 1 earlier against later frames, 2 the two
    diagonals, 3 middle against outer pitches, 4 middle against outer frames. Widths go
    through the powers of two up to :data:`WIDEST`; first classes through the circle of fifths.
    """
    out = []
    for i in range(n):
        kind, width = i % 5, WIDEST >> i % 3
        height = 8 if kind == 3 else 6 if i % 2 else 4
        out.append((kind, i * 7 % 12, height, width))
    return out


def _areas(kind: int, low: int, high: int, width: int) -> tuple[list, list]:
    """Rectangles (pitch from, to, frame from, to) of either side of a filter."""
    mid, half, a, b = low + (high - low) // 2, width // 2, low + (high - low) // 4, high - (high - low) // 4
    q, r = width // 4, width - width // 4
    return {
        0: ([(low, mid, 0, width)], [(mid, high, 0, width)]),
        1: ([(low, high, 0, half)], [(low, high, half, width)]),
        2: ([(low, mid, 0, half), (mid, high, half, width)], [(mid, high, 0, half), (low, mid, half, width)]),
        3: ([(a, b, 0, width)], [(low, a, 0, width), (b, high, 0, width)]),
        4: ([(low, high, q, r)], [(low, high, 0, q), (low, high, r, width)]),
    }[kind]


_FILTERS = [_areas(kind, low, low + high, width) for kind, low, high, width in filters()]


def codes(frames: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The packed integer of each frame that the widest filter fits behind, and whether it may vote."""
    n = len(frames) - WIDEST + 1
    if n <= 0:
        return np.empty(0, np.uint32), np.empty(0, bool)
    image = np.zeros((len(frames) + 1, 25))
    image[1:, 1:] = np.concatenate([frames, frames], axis=1, dtype=np.float64)
    image = image.cumsum(axis=0).cumsum(axis=1)
    out = np.zeros(n, np.uint32)
    for areas in _FILTERS:
        sides = []
        for side in areas:
            total = np.zeros(n)
            for p, q, s, t in side:
                total += image[t : t + n, q] - image[t : t + n, p] - image[s : s + n, q] + image[s : s + n, p]
            sides.append(total)
        value = np.log((1 + np.maximum(sides[0], 0)) / (1 + np.maximum(sides[1], 0)))
        level = (value > -LEVEL).astype(np.uint32) + (value > 0) + (value > LEVEL)
        out = (out << np.uint32(2)) | (level ^ (level >> np.uint32(1))).astype(np.uint32)
    loud = image[:, 12]
    return out, loud[WIDEST:] - loud[:-WIDEST] > 0


def fingerprint(df: DataFrame, media_col: str, decode: Callable[[object], bytes | None] | None = None) -> DataFrame:
    """Add ``n_frames``, ``codes`` (array<int>, the bits of the packed integers) and ``votes`` (whether each may vote).

    The column holds WAV bytes, or values that ``decode`` turns into WAV bytes.
    """
    keep = [c for c in df.columns if c not in ("n_frames", "codes", "votes")]

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part, n, found, loud = batch.slice(at, 64), [], [], []
                for value in part.column(len(keep)):
                    data = value.as_py()
                    samples = read_wav(decode(data) if decode else data)
                    frames = chroma(samples) if samples is not None else np.zeros((0, 12), np.float32)
                    c, v = codes(frames)
                    n.append(len(frames))
                    found.append(c.view(np.int32))
                    loud.append(v)
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), pa.array(n, pa.int64()), pa.array(found, pa.list_(pa.int32())), pa.array(loud, pa.list_(pa.bool_()))], names=[*keep, "n_frames", "codes", "votes"])

    fields = [T.StructField("n_frames", T.LongType()), T.StructField("codes", T.ArrayType(T.IntegerType())), T.StructField("votes", T.ArrayType(T.BooleanType()))]
    schema = T.StructType([*(df.schema[c] for c in keep), *fields])
    return df.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{media_col}`").alias("__media")).mapInArrow(stepwise(run), schema)


def bit_errors(x: np.ndarray, y: np.ndarray, offset: int) -> tuple[int, int]:
    """(overlapping integers, differing bits) where place i of x meets place i + offset of y."""
    a, b = max(0, -offset), min(len(x), len(y) - offset)
    if b <= a:
        return 0, 0
    return b - a, int(np.bitwise_count(x[a:b] ^ y[a + offset : b + offset]).sum())


def accepted(overlap: int, errors: int) -> bool:
    return overlap >= MIN_OVERLAP and errors <= MAX_ERROR * 32 * overlap


def align(x: np.ndarray, y: np.ndarray, votes_x: np.ndarray, votes_y: np.ndarray) -> tuple[int, int, int, int] | None:
    """(votes, offset, overlap, bit errors) of the best offset of two recordings, or None if they do not match."""
    found = Queries([(0, x, votes_x)]).matches(y, votes_y)
    return found[0][1:] if found else None


class Queries:
    """The integers of some queries, sorted, and the offset histograms of recordings against them."""

    def __init__(self, rows: list[tuple[int, np.ndarray, np.ndarray]]):
        self.codes = [c for _, c, _ in rows]
        sizes = np.array([len(c) for c in self.codes], np.int64)
        flat = np.concatenate([*self.codes, np.empty(0, np.uint32)])
        own = np.repeat(np.arange(len(rows)), sizes)
        place = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        loud = np.concatenate([*(v for _, _, v in rows), np.empty(0, bool)])
        flat, own, place = flat[loud], own[loud], place[loud]
        order = np.argsort(flat, kind="stable")
        self.flat, self.own, self.place = flat[order], own[order], place[order]

    def matches(self, y: np.ndarray, votes: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        """(query, votes, offset, overlap, bit errors) of each query that the recording matches."""
        at = np.flatnonzero(votes)
        first, last = np.searchsorted(self.flat, y[at], "left"), np.searchsorted(self.flat, y[at], "right")
        some = last > first
        at, first, count = at[some], first[some], (last - first)[some]
        if not len(at):
            return []
        # Pairs of equal integers are summed up in steps of a bounded number of them.
        span = 1 << 32
        keys, sums = np.empty(0, np.int64), np.empty(0, np.int64)
        ends = np.cumsum(count)
        total, done = int(ends[-1]), 0
        while done < total:
            upto = min(total, done + STEP_PAIRS)
            pair = np.arange(done, upto)
            row = np.searchsorted(ends, pair, "right")
            entry = first[row] + (pair - (ends[row] - count[row]))
            key = self.own[entry] * span + (at[row] - self.place[entry] + (span >> 1))
            k, n = np.unique(np.concatenate([keys, key]), return_inverse=True)
            sums, keys = np.bincount(n, np.concatenate([sums, np.ones(len(key), np.int64)])).astype(np.int64), k
            done = upto
        good = sums >= MIN_VOTES
        keys, sums = keys[good], sums[good]
        out, query = [], keys // span
        offset = keys % span - (span >> 1)
        for q in np.unique(query).tolist():
            mine = np.flatnonzero(query == q)
            top = mine[sums[mine] == sums[mine].max()]
            tried = [(bit_errors(self.codes[q], y, int(offset[i])), int(offset[i])) for i in top.tolist()]
            (overlap, errors), best = min(tried, key=lambda t: (t[0][1], t[1]))
            if accepted(overlap, errors):
                out.append((q, int(sums[mine].max()), best, overlap, errors))
        return out


_MATCHED = "query long, n_matches long, error double, short long, id long, offset long, votes long, overlap long, bit_errors long"


def _searching(queries: list[tuple[int, bytes, bytes]]):
    """An Arrow function over (id, copies, codes, votes): a summary of each query's matches a task."""

    def run(batches):
        block = Queries([(i, np.frombuffer(c, np.uint32), np.frombuffer(v, bool)) for i, c, v in queries])
        count: dict[int, int] = {}
        best: dict[int, tuple] = {}
        for batch in batches:
            for own, copies, c, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                for q, votes, offset, overlap, errors in block.matches(np.frombuffer(c, np.uint32), np.frombuffer(v, bool)):
                    row = (errors / (32 * overlap), -overlap, own, offset, votes, overlap, errors)
                    count[q] = count.get(q, 0) + copies
                    best[q] = min(best.get(q, row), row)
        rows = [(queries[q][0], n, *best[q]) for q, n in count.items()]
        kinds = (pa.int64(), pa.int64(), pa.float64(), *(pa.int64(),) * 6)
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 9, kinds)], names=[x.split()[0] for x in _MATCHED.split(", ")])

    return run


def _packed(prints: DataFrame) -> DataFrame:
    """Integers and votes as bytes."""

    def run(batches):
        for batch in batches:
            c = [np.asarray(x.values if x.is_valid else [], np.int32).tobytes() for x in batch.column(1)]
            v = [np.asarray(x.values.to_numpy(zero_copy_only=False) if x.is_valid and len(x.values) else [], bool).tobytes() for x in batch.column(2)]
            h = [xxhash.xxh3_64_intdigest(a + b) - (1 << 63) for a, b in zip(c, v)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(c, pa.binary()), pa.array(v, pa.binary()), pa.array(h, pa.int64())], names=["id", "c", "v", "h"])

    return prints.mapInArrow(stepwise(run), "id long, c binary, v binary, h long")


def search(prints: DataFrame, queries: DataFrame, id_col: str = "doc_id", block_codes: int = BLOCK_CODES) -> DataFrame:
    """One row a query that matches: query, n_matches, id, offset, votes, overlap and bit_errors of its best match.

    Both tables hold an id, ``codes`` and ``votes`` as :func:`fingerprint` gives them. Every
    query is aligned with every recording; ``n_matches`` counts them all, the query's own
    recording included.
    """
    spark = prints.sparkSession
    folder = scratch(spark, "chroma")
    chosen = [F.col(id_col).cast("long").alias("id"), "codes", "votes"]
    spoken = F.size("codes") > 0
    # Recordings with equal integers are one class, told by 64-bit hashes and compared by bytes.
    classes = _packed(prints.filter(spoken).select(*chosen)).groupBy("h", "c", "v").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies"))
    classes.select("id", "copies", "c", "v").write.parquet(f"{folder}/classes")
    classes = spark.read.schema("id long, copies long, c binary, v binary").parquet(f"{folder}/classes")
    _packed(queries.filter(spoken & F.col(id_col).isNotNull()).select(*chosen)).select("id", "c", "v").write.parquet(f"{folder}/queries")
    asked = spark.read.schema("id long, c binary, v binary").parquet(f"{folder}/queries")
    total = asked.agg(F.sum(F.length("c") / 4)).first()[0] or 0
    blocks = max(1, math.ceil(total / block_codes))
    found = None
    for k in range(blocks):
        # About block_codes integers whatever the number of queries.
        block = asked.filter(F.pmod(F.xxhash64("id"), F.lit(blocks)) == k)
        rows = [(r.id, bytes(r.c), bytes(r.v)) for r in block.toLocalIterator()]
        part = classes.mapInArrow(stepwise(_searching(rows)), _MATCHED)
        found = part if found is None else found.unionByName(part)
    least = F.min(F.struct("error", "short", "id", "offset", "votes", "overlap", "bit_errors")).alias("b")
    best = found.groupBy("query").agg(F.sum("n_matches").alias("n_matches"), least)
    return best.select("query", "n_matches", "b.id", "b.offset", "b.votes", "b.overlap", "b.bit_errors")


@cache
def _tones() -> np.ndarray:
    """Samples of two octaves of tones of 128 ms, with one harmonic."""
    t = np.arange(RATE * 128 // 1000) / RATE
    hz = 261.625565 * 2.0 ** (np.arange(24) / 12)
    swell = np.minimum(1, np.minimum(t, t[::-1]) / 0.008)
    return sum(np.sin(2 * np.pi * h * hz[:, None] * t) / h for h in (1, 2)) * swell * 0.35


def tune(values: list[float] | None, first: int = 0, last: int | None = None, noise: float = 0.0, lead: int = 0) -> bytes | None:
    """A deterministic recording of a vector: each number sounds for 128 ms, its size picks the pitch class.

    An excerpt by ``first`` and ``last``, with a noise floor and samples of silence in front,
    stands for another take of the same recording.
    """
    if not values:
        return None
    x = np.array([0.0 if v is None or v != v else v for v in values], np.float64)
    place = np.arange(len(x))
    # Numbers of a unit vector spread about 1 / sqrt(n); twelve classes of like frequency.
    spread = np.clip(x * math.sqrt(len(x)), -6, 6)
    even = np.array([0.5 * (1 + math.erf(v / math.sqrt(2))) for v in spread.tolist()])
    tone = np.minimum((even * 12).astype(int), 11) + 12 * (place % 2)
    out = _tones()[tone[first:last]].reshape(-1)
    if noise:
        out = out + noise * np.random.Generator(np.random.Philox(key=len(x))).standard_normal(len(out))
    return write_wav(np.concatenate([np.zeros(lead), out]))
