"""N-gram Jaccard join (operator 4): size-banded tiles with hashed bitmaps, exact verification.

A document's set holds the 64-bit hashes of its distinct word shingles. Equal sets are one
class, known by a hash of the set. For the classes:

1. Each set lists its first shingles in an order that all share: shingles of crowded hash
   buckets last, else by hash. Two sets of similarity t share one of the first
   n - ceil(t n) + 1. With ``listed=None`` all of these are listed. By default a set of which
   at least 75 % are uncrowded lists its first :data:`LISTED`: the order of the uncrowded is
   random and at least two thirds of their union are shared, so that a pair is missed with odds
   under 1e-11 (1e-16 without crowded ones), which is less than hashes that collide may cost.
   The whole prefix of long texts does not fit the disk that the check tool allows.
2. Rows (shingle, set) that no other set has are dropped; the others meet in tiles of one
   shingle and one band of sizes, each band also visited by the next one, as sets whose
   sizes differ more cannot be similar.
3. In a tile, bit counts of the sets' bitmaps bound the overlap from above; a bitmap has
   about a bit a shingle, in the last round four, and is folded to the size of the smaller one.
4. Pairs that pass are verified by exact intersection of the sorted arrays. First each set
   with one earlier set of each tile, and with those before it that have no pair in the tile
   yet, so that every set that passes with any is in a pair and stays for the later rounds;
   then, with components known, with one of another
   component; last all pairs that pass between different components, each by the tile of its least shared listed shingle alone.
   No group's pairs are all emitted, no link is lost.

Only a fixed table (a level a bucket) is sent to all tasks.

Defined results: null or empty texts have size 0 and are linked with nothing; repeated rows
are copies; a null id never names a component that has another id; empty tables give empty
results; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import components
from .common import scratch, stepwise

SHINGLE_WORDS, PERCENT = 5, 80
#: Listed shingles of sets that are mostly uncrowded; None lists the whole prefix of every set.
LISTED: int | None = 24
BUCKETS, CHUNKS = 1 << 18, 64
#: Odd multipliers that mix word hashes into shingle hashes.
MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5], dtype=np.uint64)

_space = np.zeros(256, bool)
_space[[0x20, *range(0x09, 0x0E)]] = True
_rng = np.random.Generator(np.random.Philox(key=97))
_byte = _rng.integers(1, 1 << 62, 256, dtype=np.uint64) | np.uint64(1)
_byte[ord("A") : ord("Z") + 1] = _byte[ord("a") : ord("z") + 1]  # lower case
_base = np.uint64(0x5851F42D4C957F2D)
_inverse = np.uint64(pow(0x5851F42D4C957F2D, -1, 1 << 64))


def _stir(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def word_hashes(data: bytes) -> np.ndarray:
    """A 64-bit hash of each word of UTF-8 text, by prefix sums over its bytes."""
    b = np.frombuffer(data, np.uint8)
    if not len(b):
        return np.empty(0, np.uint64)
    inside = ~_space[b]
    edge = np.diff(np.concatenate([[0], inside.view(np.int8), [0]]))
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    if not len(starts):
        return np.empty(0, np.uint64)
    powers = np.cumprod(np.full(len(b), _base, np.uint64))
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_byte[b] * powers)])
    back = np.cumprod(np.full(len(b), _inverse, np.uint64))
    return _stir((sums[ends] - sums[starts]) * back[starts] + (ends - starts).astype(np.uint64))


def shingle_set(text: str | None, width: int = SHINGLE_WORDS) -> np.ndarray:
    """Sorted distinct shingle hashes of a whole text."""
    w = word_hashes((text or "").encode("utf-8", "surrogatepass"))
    if not len(w):
        return w
    if len(w) < width:
        return _stir(np.array([sum((int(x) * pow(int(MIX[0]), i + 2, 1 << 64) for i, x in enumerate(w)), len(w)) & (1 << 64) - 1], np.uint64))
    n = len(w) - width + 1
    mixed = w[:n] * MIX[0]
    for k in range(1, width):
        mixed = mixed + w[k : n + k] * MIX[k % len(MIX)] * np.uint64(k // len(MIX) * 2 + 1)
    return np.unique(_stir(mixed))


def _bucket(s: np.ndarray) -> np.ndarray:
    return (s >> np.uint64(64 - BUCKETS.bit_length() + 1)).astype(np.int64)


def _count(width):
    def run(batches):
        total = np.zeros(BUCKETS, np.int32)
        for batch in batches:
            for text in batch.column(0):
                np.add.at(total, _bucket(shingle_set(text.as_py(), width)), 1)
        if total.any():
            parts = total.reshape(CHUNKS, -1)
            yield pa.RecordBatch.from_pydict({"chunk": pa.array(range(CHUNKS), pa.int32()), "counts": pa.array([p.tobytes() for p in parts], pa.binary())})

    return run


def _merge(batches):
    sums: dict[int, np.ndarray] = {}
    for batch in batches:
        for chunk, counts in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            sums[chunk] = sums.get(chunk, 0) + np.frombuffer(counts, np.int32).astype(np.int64)
    for chunk, v in sums.items():
        yield pa.RecordBatch.from_pydict({"chunk": pa.array([chunk], pa.int32()), "counts": pa.array([v.tobytes()], pa.binary())})


def crowded_levels(texts: DataFrame, width: int = SHINGLE_WORDS) -> np.ndarray:
    """A level for each hash bucket: 0 where its count is ordinary, more the more crowded it is."""
    rows = texts.mapInArrow(stepwise(_count(width)), "chunk int, counts binary").repartition("chunk").mapInArrow(_merge, "chunk int, counts binary").collect()
    total = np.zeros((CHUNKS, BUCKETS // CHUNKS), np.int64)
    for r in rows:  # one row a chunk
        total[r.chunk] = np.frombuffer(r.counts, np.int64)
    total = total.reshape(-1)
    middle = np.median(total)
    spread = 1.5 * np.median(np.abs(total - middle)) + 1
    over = (total - middle) / (8 * spread + 24)
    return np.where(over > 1, np.minimum(2 + np.log2(np.maximum(over, 1)), 40), 0).astype(np.uint8)


def bitmap(s: np.ndarray, scale: int = 1) -> bytes:
    """A bit for each shingle's hash modulo the bitmap's size: a power of two, ``scale`` to twice that a shingle."""
    bits = (64 << max(0, math.ceil(math.log2(len(s) / 64)))) * scale
    out = np.zeros(bits, np.uint8)
    out[(s & np.uint64(bits - 1)).astype(np.int64)] = 1
    return np.packbits(out, bitorder="little").tobytes()


def _band(n: int, percent: int) -> int:
    return int(math.floor(math.log(n) / math.log(100 / percent) + 1e-9))


def _sets(levels, width, percent, listed):
    def run(batches):
        seen: set[int] = set()
        for batch in batches:
            out = []
            for text in batch.column(1):
                s = shingle_set(text.as_py(), width)
                n = len(s)
                if not n:
                    out.append((0, None, None, None, None))
                    continue
                a = xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63)
                if a in seen:
                    out.append((n, a, None, None, None))
                    continue
                if len(seen) > 200_000:
                    seen.clear()
                seen.add(a)
                level = levels[_bucket(s)]
                most = n - -(-percent * n // 100) + 1
                if listed and (level == 0).sum() >= 0.75 * n:
                    most = min(most, listed)
                first = s[np.lexsort((s, level))[:most]]
                out.append((n, a, first.view(np.int64), bitmap(s), _band(n, percent)))
            n, a, first, bits, band = zip(*out)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.int64()), pa.array(first, pa.list_(pa.int64())), pa.array(bits, pa.binary()), pa.array(band, pa.int32())], names=["doc_id", "n_shingles", "a", "first", "bits", "band"])

    return run


def most_overlap(x: bytes, y: bytes, nx: int, ny: int) -> int:
    """An upper bound of the overlap of two sets from their bitmaps."""
    p, q = (np.frombuffer(v, np.uint64) for v in (x, y))
    p, q = _fold(p[None, :], min(len(p), len(q)))[0], _fold(q[None, :], min(len(p), len(q)))[0]
    return int(min(nx - np.bitwise_count(p & ~q).sum(), ny - np.bitwise_count(q & ~p).sum()))


def _fold(m: np.ndarray, words: int) -> np.ndarray:
    while m.shape[1] > words:
        half = m.shape[1] // 2
        m = m[:, :half] | m[:, half:]
    return m


class _Tile:
    """The rows of one tile by bitmap width; compares a row with all before it."""

    def __init__(self, percent):
        self.percent, self.rows = percent, {}

    def close(self, mode: str, token: int):
        """Pairs (x, y) that pass: each set with its first earlier match and the earlier ones not yet
        in a pair (``first``), with one earlier match of another label, another in each tile
        (``one``), or with ``all`` of them."""
        cross = mode != "first"
        paired = np.zeros(len(self.rows), bool)
        home = np.array([r[0] for r in self.rows], bool)
        a = np.array([r[1] for r in self.rows], np.int64)
        n = np.array([r[2] for r in self.rows], np.int64)
        label = np.array([r[4] for r in self.rows], np.int64)
        if not home.any() or (cross and (label == label[0]).all()):
            return
        if mode == "all":
            counts = np.array([len(r[5]) for r in self.rows])
            columns = np.arange(counts.max())[None, :]
            lists = np.zeros((len(self.rows), counts.max()), np.int64)
            for i, r in enumerate(self.rows):
                lists[i, : counts[i]] = r[5]
        widths = np.array([len(r[3]) // 8 for r in self.rows])
        maps = {w: (np.flatnonzero(widths == w), np.array([np.frombuffer(self.rows[i][3], np.uint64) for i in np.flatnonzero(widths == w)])) for w in sorted(set(widths.tolist()))}
        for w, (own, bits) in maps.items():
            folded = {v: (at, m, _fold(m, min(v, w))) for v, (at, m) in maps.items()}
            for i, row in zip(own.tolist(), bits):
                matched = False
                for v, (at, m, f) in folded.items():
                    before = at < i
                    if cross:
                        before &= label[at] != label[i]
                    elif matched:
                        before &= ~paired[at]
                    if not home[i]:
                        before &= home[at]
                    before &= (100 * n[at] >= self.percent * n[i]) & (self.percent * n[at] <= 100 * n[i])
                    pick = np.flatnonzero(before)
                    if not len(pick):
                        continue
                    mine = _fold(row[None, :], min(v, w))
                    other = f[pick]
                    most = np.minimum(n[i] - np.bitwise_count(mine & ~other).sum(axis=1, dtype=np.int64), n[at[pick]] - np.bitwise_count(other & ~mine).sum(axis=1, dtype=np.int64))
                    good = pick[100 * most >= self.percent * (n[i] + n[at[pick]] - most)]
                    if mode == "one":
                        good = good[[(int(a[i]) ^ token) * 0x9E3779B97F4A7C15 % (1 << 64) % len(good)]] if len(good) else good
                    elif cross:
                        # The same pair passes in each tile that it shares: the least shared shingle's tile gives it.
                        common = np.isin(lists[at[good]], lists[i][: counts[i]]) & (columns < counts[at[good], None])
                        least = np.where(common, lists[at[good]], np.iinfo(np.int64).max).min(axis=1)
                        good = good[least == token]
                    elif len(good):
                        new = ~paired[at[good]]
                        new[0] |= not matched
                        good = good[new]
                        paired[i] = paired[at[good]] = matched = True
                    for j in at[good].tolist():
                        yield int(a[i]), int(a[j])


def _compare(percent, mode):
    """Rows sorted by tile: token, tile, home, a, n, bits, label, listed shingles (null but for cross)."""

    def run(batches):
        seen, key, rows, out = set(), None, [], []

        def finish():
            if len(rows) > 1:
                t = _Tile(percent)
                t.rows = rows
                for x, y in t.close(mode, key[0]):
                    pair = (x, y) if x < y else (y, x)
                    if pair not in seen:
                        if len(seen) > 300_000:
                            seen.clear()
                        seen.add(pair)
                        out.append(pair)

        def flush():
            x, y = zip(*out) if out else ((), ())
            out.clear()
            return pa.RecordBatch.from_pydict({"x": pa.array(x, pa.int64()), "y": pa.array(y, pa.int64())})

        for batch in batches:
            for token, tile, home, a, n, bits, label, listed in zip(*(batch.column(i).to_pylist() for i in range(8))):
                if (token, tile) != key:
                    finish()
                    key, rows = (token, tile), []
                if not rows or rows[-1][1] != a:
                    rows.append((home, a, n, bits, label, listed))
            if out:
                yield flush()
        finish()
        yield flush()

    return run


def _candidates(live: DataFrame, sets: DataFrame, labels: DataFrame | None, percent: int, mode: str) -> DataFrame:
    listed = F.col("list") if mode == "all" else F.lit(None).cast("array<long>").alias("list")
    rows = live.join(sets.select("a", "n", "bits", "band", listed), "a")
    rows = rows.join(labels, rows["a"] == labels["node"], "left").drop("node") if labels is not None else rows.withColumn("label", F.lit(None).cast("long"))
    rows = rows.withColumn("label", F.coalesce("label", "a"))
    tiles = F.explode(F.array(F.struct(F.col("band").alias("tile"), F.lit(True).alias("home")), F.struct((F.col("band") - 1).alias("tile"), F.lit(False).alias("home"))))
    rows = rows.withColumn("t", tiles).select("token", F.col("t.tile").alias("tile"), F.col("t.home").alias("home"), "a", "n", "bits", "label", "list")
    rows = rows.repartition("token", "tile").sortWithinPartitions("token", "tile", F.desc("home"), "a")
    return rows.mapInArrow(stepwise(_compare(percent, mode)), "x long, y long").distinct()


def _verify(percent):
    def run(batches):
        for batch in batches:
            xs, ys = [], []
            for x, y, s, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3)):
                s, t = (np.frombuffer(v.as_py(), np.uint64) for v in (s, t))
                both = len(np.intersect1d(s, t, assume_unique=True))
                if 100 * both >= percent * (len(s) + len(t) - both):
                    xs.append(x)
                    ys.append(y)
            yield pa.RecordBatch.from_pydict({"x": pa.array(xs, pa.int64()), "y": pa.array(ys, pa.int64())})

    return run


def _arrays(width):
    """Arrays of texts whose set's hash is the class's: an id may belong to several texts."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                sets = [shingle_set(t.as_py(), width).tobytes() for t in part.column(1)]
                good = [xxhash.xxh3_64_intdigest(s) - (1 << 63) == a for a, s in zip(part.column(0).to_pylist(), sets)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.binary())], names=["a", "s"]).filter(pa.array(good, pa.bool_()))

    return run


def _widened(batches):
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([bitmap(np.frombuffer(x.as_py(), np.uint64), 4) for x in batch.column(1)], pa.binary())], names=["a", "bits"])


def _linked(pairs: DataFrame, arrays: DataFrame, percent: int) -> DataFrame:
    left = arrays.select(F.col("a").alias("x"), F.col("s").alias("sx"))
    right = arrays.select(F.col("a").alias("y"), F.col("s").alias("sy"))
    return pairs.join(left, "x").join(right, "y").select("x", "y", "sx", "sy").mapInArrow(stepwise(_verify(percent)), "x long, y long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE_WORDS, percent: int = PERCENT, listed: int | None = LISTED) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (smallest id reachable by links)."""
    spark = docs.sparkSession
    folder = scratch(spark, "jaccard")

    def kept(df: DataFrame, name: str) -> DataFrame:
        df.write.parquet(f"{folder}/{name}")
        return spark.read.schema(df.schema).parquet(f"{folder}/{name}")

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    levels = crowded_levels(texts.select("text"), width)
    rows = kept(texts.mapInArrow(stepwise(_sets(levels, width, percent, listed)), "doc_id long, n_shingles long, a long, first array<long>, bits binary, band int"), "sets")
    sets = rows.filter("first is not null").groupBy("a").agg(F.first("n_shingles").alias("n"), F.first("bits").alias("bits"), F.first("band").alias("band"), F.first("first").alias("list"))
    lists = rows.filter("first is not null").select("a", F.explode("first").alias("token"))
    # A shingle stays if two sets list it, which the smallest and the largest set tell.
    shared = lists.groupBy("token").agg(F.min("a").alias("low"), F.max("a").alias("high")).filter("low < high").select("token")
    live = kept(lists.join(shared, "token").select("token", "a").distinct(), "live")
    checked = kept(_candidates(live, sets, None, percent, "first"), "first")
    nodes = kept(checked.select(F.explode(F.array("x", "y")).alias("a")).distinct(), "nodes")
    # One text of each class that is in a pair.
    heads = rows.filter("first is not null").groupBy("a").agg(F.min("doc_id").alias("doc_id")).join(nodes, "a")
    keyed = heads.join(texts, "doc_id").select("a", "text").mapInArrow(stepwise(_arrays(width)), "a long, s binary")
    arrays = kept(keyed.dropDuplicates(["a"]), "arrays")
    links = kept(_linked(checked, arrays, percent), "links")
    open_rows = live.join(nodes, "a", "left_semi")
    wide = kept(arrays.mapInArrow(stepwise(_widened), "a long, bits binary"), "wide")
    fine = sets.drop("bits").join(wide, "a")
    for mode, of in (("one", sets), ("all", fine)):
        labels = kept(components(links), f"labels-{mode}")
        more = kept(_candidates(open_rows, of, labels, percent, mode).join(checked, ["x", "y"], "left_anti"), mode)
        checked = checked.unionByName(more)
        links = links.unionByName(kept(_linked(more, arrays, percent), f"links-{mode}"))
    labels = components(links)
    classes = rows.filter("a is not null").groupBy("a").agg(F.min("doc_id").alias("low")).join(labels, F.col("a") == F.col("node"), "left")
    classes = classes.select("a", "low", F.coalesce("label", "a").alias("label"))
    least = classes.groupBy("label").agg(F.min("low").alias("component_id"))
    named = classes.join(least, "label").select("a", "component_id")
    return rows.join(named, "a", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
