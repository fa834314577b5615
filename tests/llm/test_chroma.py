"""Chroma fingerprints and their alignment against a brute-force version, and edge cases."""

import struct
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from sieveline.llm import chroma
from sieveline.llm.queries import QUERIES


def _unsigned(xs):
    return [x & 0xFFFFFFFF for x in xs]


def _brute(x, y, votes_x, votes_y):
    """(votes, offset, overlap, errors) by a full table of equal integers."""
    seen = Counter(j - i for i, a in enumerate(x) for j, b in enumerate(y) if a == b and votes_x[i] and votes_y[j])
    best = None
    top = max(seen.values(), default=0)
    for offset in sorted(o for o, n in seen.items() if n == top):
        pairs = [(x[i], y[i + offset]) for i in range(len(x)) if 0 <= i + offset < len(y)]
        errors = sum((a ^ b).bit_count() for a, b in pairs)
        if best is None or errors < best[3]:
            best = (top, offset, len(pairs), errors)
    good = best and top >= chroma.MIN_VOTES and best[2] >= chroma.MIN_OVERLAP and best[3] <= chroma.MAX_ERROR * 32 * best[2]
    return best if good else None


@pytest.fixture(scope="module")
def vectors(spark, sf):
    made = [(10**6, None), (10**6 + 20, []), (10**6 + 40, [0.1, 0.2]), (10**6 + 60, [None, float("nan")] * 30), (None, [0.1] * 64)]
    table = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", F.col("embedding").cast("array<double>")).filter("vec_id < 120")
    out = table.unionByName(spark.createDataFrame(made, "vec_id long, embedding array<double>"))
    out = out.unionByName(out.filter("vec_id in (7, 40)"))  # repeated rows
    return out.unionByName(out.filter("vec_id = 3").withColumn("vec_id", F.lit(5000).cast("long"))).withColumn("codes", F.lit("x")).withColumn("id", F.lit(1))


def test_image_filters_equal_plain_sums():
    rng = np.random.default_rng(2)
    frames = rng.random((40, 12)).astype(np.float32)
    frames[5:25] = 0
    got, votes = chroma.codes(frames)
    assert len(got) == 40 - chroma.WIDEST + 1
    assert votes.tolist() == [bool(frames[i : i + chroma.WIDEST].any()) for i in range(len(got))]
    sure = 0
    for at in range(len(got)):
        code, plain = 0, True
        for kind, low, height, width in chroma.filters():
            window = [[float(frames[at + t, (low + p) % 12]) for p in range(height)] for t in range(width)]

            def inside(p, t, kind=kind, height=height, width=width):
                if kind == 0:
                    return p < height // 2
                if kind == 1:
                    return t < width // 2
                if kind == 2:
                    return (p < height // 2) == (t < width // 2)
                if kind == 3:
                    return height // 4 <= p < height - height // 4
                return width // 4 <= t < width - width // 4

            a = sum(window[t][p] for t in range(width) for p in range(height) if inside(p, t))
            b = sum(window[t][p] for t in range(width) for p in range(height) if not inside(p, t))
            v = float(np.log((1 + a) / (1 + b)))
            plain &= min(abs(v - x) for x in (-chroma.LEVEL, 0, chroma.LEVEL)) > 1e-9
            code = code << 2 | [0, 1, 3, 2][(v > -chroma.LEVEL) + (v > 0) + (v > chroma.LEVEL)]
        assert not plain or code == got[at]  # a value on a bound may fall on either side of it
        sure += plain
    assert sure > 5


def test_pure_tones_fall_into_their_pitch_class():
    t = np.arange(chroma.RATE) / chroma.RATE
    for k in range(12):
        frames = chroma.chroma(np.sin(2 * np.pi * 440 * 2 ** (k / 12) * t).astype(np.float32))
        assert set(frames.argmax(axis=1).tolist()) == {k}
    assert not chroma.chroma(np.zeros(5000, np.float32)).any() and len(chroma.chroma(np.zeros(10, np.float32))) == 0


def test_wav_formats():
    x = (np.sin(np.arange(4000) / 5) * 0.5).astype(np.float32)

    def wav(kind, bits, body, channels=1, rate=chroma.RATE):
        head = struct.pack("<HHIIHH", kind, channels, rate, rate * channels * bits // 8, channels * bits // 8, bits)
        return b"RIFF\0\0\0\0WAVE" + b"LIST" + struct.pack("<I", 3) + b"abc\0" + b"fmt " + struct.pack("<I", 16) + head + b"data" + struct.pack("<I", len(body)) + body

    twice = np.repeat(x, 2)
    i24 = (x * 8388607).astype("<i4").view(np.uint8).reshape(-1, 4)[:, :3].tobytes()
    for data in (wav(3, 32, x.tobytes()), wav(1, 16, (x * 32767).astype("<i2").tobytes()), wav(1, 24, i24), wav(1, 8, (x * 127 + 128).astype(np.uint8).tobytes()), wav(3, 32, twice.tobytes(), 2), chroma.write_wav(x)):
        assert np.abs(chroma.read_wav(data) - x).max() < 0.02
    assert abs(len(chroma.read_wav(wav(3, 32, twice.tobytes(), 1, 2 * chroma.RATE))) - len(x)) <= 1
    for bad in (None, b"", b"RIFF", b"RIFF\0\0\0\0WAVEdata", wav(7, 16, b"ab"), wav(1, 16, b"", 0)):
        assert chroma.read_wav(bad) is None


def test_search_against_brute_force(spark, vectors, monkeypatch):
    prints = chroma.fingerprint(vectors, "embedding", chroma.tune).cache()
    assert prints.count() == vectors.count() and prints.columns == ["vec_id", "embedding", "id", "n_frames", "codes", "votes"]
    rows = [(r.vec_id, _unsigned(r.codes), r.votes) for r in prints.collect()]
    assert {len(c) for i, c, _ in rows if i in (10**6, 10**6 + 20, 10**6 + 40)} == {0}

    def take(values):
        return chroma.tune(values, first=10, last=50, noise=0.02, lead=300)

    takes = chroma.fingerprint(vectors.filter("vec_id % 20 = 0").dropDuplicates(["vec_id"]), "embedding", take).cache()
    asked = [(r.vec_id, _unsigned(r.codes), r.votes) for r in takes.collect()]
    expect = {}
    for q, c, v in asked:
        found = [(m[3] / (32 * m[2]), -m[2], i, m) for i, d, w in rows if (m := _brute(c, d, v, w))]
        if found:
            _, _, best, m = min(found, key=lambda x: (x[0], x[1], x[2] is None, x[2] or 0))
            expect[q] = (len(found), best, m[1], m[0], m[2], m[3])
    for block in (chroma.BLOCK_CODES, 100):  # all queries at once, then a few at a time
        monkeypatch.setattr(chroma, "STEP_PAIRS", 7 if block == 100 else 1 << 20)
        got = {r.query: (r.n_matches, r.id, r.offset, r.votes, r.overlap, r.bit_errors) for r in chroma.search(prints, takes, "vec_id", block).collect()}
        assert got == expect
    assert all(expect[q][1] == q for q in range(0, 120, 20)) and expect[40][0] >= 2
    assert chroma.search(prints.limit(0), takes, "vec_id").count() == 0 and chroma.search(prints, takes.limit(0), "vec_id").count() == 0


def test_alike_recordings_are_all_counted(spark):
    """A third of the recordings are one drone, a few take silence."""
    drone = [0.05] * 64
    made = [(i, drone) for i in range(60)] + [(100 + i, [((i * 37 + k * k * 11) % 23 - 11) / 50 for k in range(64)]) for i in range(100)]
    prints = chroma.fingerprint(spark.createDataFrame(made, "vec_id long, embedding array<double>"), "embedding", chroma.tune)
    got = {r.query: r.n_matches for r in chroma.search(prints, prints.filter("vec_id in (0, 20, 40)"), "vec_id").collect()}
    assert got == {0: 60, 20: 60, 40: 60}
    silent = chroma.fingerprint(spark.createDataFrame([(1, chroma.write_wav(np.zeros(60000)))], "vec_id long, wav binary"), "wav")
    assert silent.first().n_frames > 100 and chroma.search(silent, silent, "vec_id").count() == 0


def test_query_finds_each_take(spark):
    out = QUERIES["op7_chroma"](spark, "/root/testdata/sf0.01").collect()
    asked = [r for r in out if r.vec_id % 20 == 0]
    assert len(out) == 500 and all(r.n_codes > 0 for r in out)
    # Recall of the true recording among the queries, and its place.
    assert sum(r.match_id == r.vec_id for r in asked) >= 0.95 * len(asked) and {r.offset for r in asked} <= {23, 24}
    assert all(r.match_id is None for r in out if r.vec_id % 20)
