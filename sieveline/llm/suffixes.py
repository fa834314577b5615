"""Suffix-array deduplication (operator 1): longest-previous-factor arrays over sparse suffixes.

Bytes covered by a string of L bytes that occurs elsewhere are removed, all occurrences or
all but the first. A suffix array of the whole corpus is not needed for that, since only
windows of L bytes matter:

1. Every window has an anchor, the leftmost of its smallest K-gram hashes. Windows with one
   anchor position form a segment of at most L - K + 1 windows; equal windows have equal
   anchors. One row a segment: (anchor hash, segment hash, place).
2. Anchors seen once are unique, and so are all windows of their segments. Segments that
   are equal as a whole are repeated as a whole. Both follow from one map-side combined
   aggregate an anchor, however many copies there are.
3. Only anchors with different segments remain. One segment of each kind is cut out of its
   text, and the segments of each anchor are laid into a block whose suffix array, in the
   order of the first L bytes, is built by prefix doubling. The previous and next smaller
   positions in suffix order give each suffix's earlier match, that is where its
   longest-previous-factor array reaches L; being someone's earlier match marks the first
   occurrence.
4. Anchors with over :data:`CROWDED` different segments would make a block without bound: their
   windows are dealt out one by one and counted by 128-bit hashes, again map-side combined.

Positions are bytes. Defined results: null text is empty; texts shorter than L are kept
whole; rows that repeat an id and text are documents of their own, each a copy of the
other (with ``keep_first`` such twins all stay); rows that repeat an id with other texts are told apart by the text's hash; an empty
table gives an empty one; other columns are carried unless they clash with the new ones.
"""

from __future__ import annotations


import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import scratch

LENGTH, K = 200, 32
#: Longer texts are looked at in overlapping pieces.
PIECE = 1 << 19
#: Bytes of segments in one suffix array; different segments of an anchor before it is spread out.
BLOCK_BYTES, CROWDED = 1 << 20, 2000

_rng = np.random.Generator(np.random.Philox(key=11))
_byte = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_base = np.uint64(0x2545F4914F6CDD1D)
_inverse = np.uint64(pow(0x2545F4914F6CDD1D, -1, 1 << 64))
_powers = np.empty(0, np.uint64)
_backs = np.empty(0, np.uint64)


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers, _backs
    if len(_powers) < n:
        _powers = np.cumprod(np.full(n, _base, np.uint64))
        _backs = np.cumprod(np.full(n, _inverse, np.uint64))
    return _powers[:n], _backs[:n]


def gram_hashes(b: np.ndarray, k: int) -> np.ndarray:
    """A 64-bit hash of each k bytes."""
    powers, backs = _tables(len(b))
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_byte[b] * powers)])
    h = (sums[k:] - sums[:-k]) * backs[: len(b) - k + 1]
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def _sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    n = len(x)
    pad = np.concatenate([x, np.full(-n % w, np.iinfo(x.dtype).max, x.dtype)]).reshape(-1, w)
    ahead = np.minimum.accumulate(pad, axis=1).reshape(-1)
    back = np.minimum.accumulate(pad[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    return np.minimum(back[: n - w + 1], ahead[w - 1 : n])


def segments(data: bytes, length: int = LENGTH, k: int = K):
    """(first window, last window, anchor hash) arrays of a text's segments."""
    firsts, lasts, anchors = [], [], []
    n, w = len(data), length - k + 1
    mask = np.uint64(PIECE * 2 - 1)
    for at in range(0, n - length + 1, PIECE):
        b = np.frombuffer(data, np.uint8, min(n - at, PIECE + length - 1), at)
        h = gram_hashes(b, k)
        place = _sliding_min((h & ~mask) | np.arange(len(h), dtype=np.uint64), w) & mask
        cuts = np.flatnonzero(np.diff(place)) + 1
        first = np.concatenate([[0], cuts])
        firsts.append(first + at)
        lasts.append(np.concatenate([cuts - 1, [len(place) - 1]]) + at)
        anchors.append(h[place[first].astype(np.int64)])
    if not firsts:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.uint64)
    return np.concatenate(firsts), np.concatenate(lasts), np.concatenate(anchors)


def suffix_order(block: np.ndarray, starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """The suffix array over some starts, by the first ``length`` bytes, and by place in it the rank
    of those bytes: suffixes that share them have one rank."""
    n = len(block)
    width = 8
    packed = np.zeros(n, np.uint64)
    for i in range(width):
        packed = (packed << np.uint64(8)) | np.concatenate([block[i:], np.zeros(min(i, n), np.uint8)])[:n].astype(np.uint64)
    rank = np.unique(packed, return_inverse=True)[1].astype(np.int64)
    while width < length:
        step = min(width, length - width)
        follow = np.concatenate([rank[step:] + 1, np.zeros(min(step, n), np.int64)])[:n]
        width += step
        if width < length:
            rank = np.unique(rank * (n + 1) + follow, return_inverse=True)[1].astype(np.int64)
        else:
            rank = rank * (n + 1) + follow
    keys = rank[starts]
    order = np.argsort(keys, kind="stable")
    return starts[order], keys[order]


def smaller_neighbours(order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each place of a suffix array, the places of the previous and next smaller positions (-1: none).

    All places at once: a place whose candidate holds a larger position goes on to the
    candidate's own candidate, as all between them are larger still; the way doubles each time.
    """
    n = len(order)
    position = np.append(order, -1)  # place -1 and n: smaller than all
    sides = []
    for step, end in ((-1, -1), (1, n)):
        found = np.append(np.arange(n) + step, end)
        left = np.arange(n)
        while len(left := left[position[found[left]] > order[left]]):
            found[left] = found[found[left]]
        sides.append(np.where(found[:n] == n, -1, found[:n]))
    return sides[0], sides[1]


def earlier_matches(order: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions whose longest previous factor has the full length, and the earlier positions they match.

    ``keys`` has, by place in suffix order, equal numbers for suffixes that share the length.
    The longest previous factor of a suffix is its match with the previous or the next
    smaller position in suffix order, whichever is longer, so that no other place need be seen.
    """
    later, source = [], []
    for places in smaller_neighbours(order):
        hit = np.flatnonzero((places >= 0) & (keys[places] == keys))
        later.append(order[hit])
        source.append(order[places[hit]])
    return np.concatenate(later), np.concatenate(source)


def longest_previous_factors(data: bytes) -> np.ndarray:
    """The longest-previous-factor array of one string: at each position, the length of the
    longest match that starts earlier."""
    n = len(data)
    out = np.zeros(n, np.int64)
    order = np.array(sorted(range(n), key=lambda i: data[i:]), np.int64)
    before, after = smaller_neighbours(order)

    def common(i, j):
        m = 0
        while max(i, j) + m < n and data[i + m] == data[j + m]:
            m += 1
        return m

    for place, i in enumerate(order.tolist()):
        out[i] = max((common(i, int(order[x])) for x in (before[place], after[place]) if x >= 0), default=0)
    return out


def _segments(length, k):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                ids, hashes, cols = [], [], []
                part = batch.slice(at, 256)
                for doc_id, th, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(2)):
                    data = (text.as_py() or "").encode("utf-8", "surrogatepass")
                    first, last, anchor = segments(data, length, k)
                    if len(first):
                        view = memoryview(data)
                        s = np.fromiter((xxhash.xxh3_64_intdigest(view[p : q + length]) for p, q in zip(first.tolist(), last.tolist())), np.uint64, len(first))
                        cols.append((first, last, anchor.view(np.int64), s.view(np.int64)))
                        ids += [doc_id] * len(first)
                        hashes.append(np.full(len(first), th))
                if cols:
                    first, last, anchor, s = (np.concatenate(c) for c in zip(*cols))
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.concatenate(hashes)), pa.array(first), pa.array(last), pa.array(anchor), pa.array(s)], names=["doc_id", "th", "p", "q", "v", "s"])

    return run


def _cut_out(length):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                rows = []
                part = batch.slice(at, 64)
                for doc_id, th, text, wanted in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(2), part.column(3).to_pylist()):
                    data = (text.as_py() or "").encode("utf-8", "surrogatepass")
                    rows += [(w["v"], w["n"], w["crowded"], doc_id, th, w["p"], w["q"], data[w["p"] : w["q"] + length]) for w in wanted]
                kinds = (pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 8, kinds)], names=["v", "n", "crowded", "doc_id", "th", "p", "q", "bytes"])

    return run


def runs(starts: np.ndarray, length: int) -> list[tuple[int, int]]:
    """Maximal [from, to) covered by strings of the length at the sorted starts."""
    if not len(starts):
        return []
    cuts = np.flatnonzero(np.diff(starts) > length) + 1
    first = np.concatenate([[0], cuts])
    last = np.concatenate([cuts - 1, [len(starts) - 1]])
    return list(zip(starts[first].tolist(), (starts[last] + length).tolist()))


def _arrays(length, keep_first):
    """Rows sorted by anchor, then document and place: repeated runs of each segment."""

    def run(batches):
        held, size, last, out = [], 0, None, []

        def finish():
            nonlocal held, size
            # Segments that are known as repeated take part, as others may match them.
            block = np.frombuffer(b"".join(r[5] for r in held), np.uint8)
            base = np.concatenate([[0], np.cumsum([len(r[5]) for r in held])])
            starts = np.concatenate([np.arange(len(r[5]) - length + 1) + o for r, o in zip(held, base)])
            later, source = earlier_matches(*suffix_order(block, starts, length))
            hit = np.unique(later if keep_first else np.concatenate([later, source]))
            owner = np.searchsorted(base, hit, "right") - 1
            for i in np.unique(owner).tolist():
                doc_id, th, p = held[i][2:5]
                if not keep_first and held[i][1] > 1:
                    continue
                out.extend((doc_id, th, p + a - int(base[i]), p + b - int(base[i])) for a, b in runs(hit[owner == i], length))
            held, size = [], 0

        def flush():
            kinds = (pa.int64(),) * 4
            batch = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out) if out else [[]] * 4, kinds)], names=["doc_id", "th", "start", "end"])
            out.clear()
            return batch

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if held and row[0] != last and size > BLOCK_BYTES:
                    finish()
                    yield flush()
                last = row[0]
                held.append(row)
                size += len(row[5])
        if held:
            finish()
        yield flush()

    return run


def _windows(length):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                cols = []
                for n, doc_id, th, p, data in zip(*(batch.column(i).slice(at, 256).to_pylist() for i in range(5))):
                    view = memoryview(data)
                    for i in range(len(data) - length + 1):
                        h = xxhash.xxh3_128_digest(view[i : i + length])
                        cols.append((h, n, doc_id, th, p + i))
                kinds = (pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*cols) if cols else [[]] * 5, kinds)], names=["h", "n", "doc_id", "th", "start"])

    return run


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, keep_first: bool = False) -> tuple[DataFrame, DataFrame]:
    """(texts as doc_id, th, text; spans as doc_id, th, start, end in bytes).

    With ``keep_first`` the first occurrence of every string, by id then position, stays.
    """
    spark = docs.sparkSession
    folder = scratch(spark, "suffixes")
    k = min(K, max(1, length // 4))

    def kept(df: DataFrame, name: str) -> DataFrame:
        df.write.parquet(f"{folder}/{name}")
        return spark.read.schema(df.schema).parquet(f"{folder}/{name}")

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("th"), F.col(text_col).cast("string").alias("text"))
    rows = texts.mapInArrow(_segments(length, k), "doc_id long, th long, p long, q long, v long, s long")
    seen = rows.groupBy("v").agg(F.count(F.lit(1)).alias("c"), F.min("s").alias("low"), F.max("s").alias("high")).filter("c > 1")
    # Written first: a join of its own can deal a hot anchor's rows over many tasks.
    seen = kept(seen.select("v", (F.col("low") != F.col("high")).alias("mixed")), "anchors")
    again = kept(rows.join(seen, "v"), "segments")
    head = F.min(F.struct("doc_id", "th", "p", "q")).alias("head")
    kinds = kept(again.filter("mixed" if not keep_first else "true").groupBy("v", "s").agg(F.count(F.lit(1)).alias("n"), head), "kinds")
    mixed = kinds.groupBy("v").agg(F.count(F.lit(1)).alias("different")).filter("different > 1")
    whole = again.join(kinds.filter("n > 1"), ["v", "s"])
    if keep_first:
        whole = whole.filter(~F.col("head").eqNullSafe(F.struct("doc_id", "th", "p", "q")))
    whole = whole.select("doc_id", "th", F.col("p").alias("start"), (F.col("q") + length).alias("end"))
    if not keep_first:
        whole = whole.unionByName(again.filter("not mixed").select("doc_id", "th", F.col("p").alias("start"), (F.col("q") + length).alias("end")))
    wanted = kinds.join(mixed, "v").select("v", "n", (F.col("different") > CROWDED).alias("crowded"), "head.*")
    wanted = wanted.groupBy("doc_id", "th").agg(F.collect_list(F.struct("v", "n", "crowded", "p", "q")).alias("wanted"))
    named = texts.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "text")
    match = F.col("d").eqNullSafe(F.col("doc_id")) & (F.col("t") == F.col("th"))
    cut = named.join(wanted, match).select("doc_id", "th", "text", "wanted").mapInArrow(_cut_out(length), "v long, n long, crowded boolean, doc_id long, th long, p long, q long, bytes binary")
    cut = kept(cut, "cut").dropDuplicates(["v", "doc_id", "th", "p"])
    plain = cut.filter("not crowded").select("v", "n", "doc_id", "th", "p", "bytes").repartition("v").sortWithinPartitions("v", "doc_id", "th", "p")
    found = plain.mapInArrow(_arrays(length, keep_first), "doc_id long, th long, start long, end long")
    spread = kept(cut.filter("crowded").select("n", "doc_id", "th", "p", "bytes").mapInArrow(_windows(length), "h binary, n long, doc_id long, th long, start long"), "windows")
    counts = spread.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct("doc_id", "th", "start")).alias("head")).filter("c > 1")
    hot = spread.join(counts, "h")
    hot = hot.filter(~F.col("head").eqNullSafe(F.struct("doc_id", "th", "start"))) if keep_first else hot.filter("n = 1")
    hot = hot.select("doc_id", "th", "start", (F.col("start") + length).alias("end"))
    return texts, whole.unionByName(found).unionByName(hot)


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, keep_first: bool = False) -> DataFrame:
    """Each document with ``n_bytes``, ``n_removed``, ``n_spans`` and ``kept``, the bytes that stay."""
    texts, spans = repeated_spans(docs, id_col, text_col, length, keep_first)
    per = spans.groupBy("doc_id", "th").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    match = F.col("d").eqNullSafe(F.col("doc_id")) & (F.col("t") == F.col("th"))
    joined = texts.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "text").join(per, match, "left").select(F.col("d").alias("doc_id"), "text", "spans.start", "spans.end")

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part, rows = batch.slice(at, 256), []
                for doc_id, text, start, end in zip(part.column(0).to_pylist(), part.column(1), part.column(2), part.column(3)):
                    data = (text.as_py() or "").encode("utf-8", "surrogatepass")
                    left, n_spans, pos, removed = [], 0, 0, 0
                    if start.is_valid:
                        a, b = start.values.to_numpy(), end.values.to_numpy()
                        order = np.argsort(a, kind="stable")
                        for x, y in zip(a[order].tolist(), b[order].tolist()):
                            if n_spans and x <= reach:
                                reach = max(reach, y)
                                continue
                            if n_spans:
                                removed, pos = removed + reach - begin, reach
                            left.append(data[pos:x])
                            begin, reach, n_spans = x, y, n_spans + 1
                        if n_spans:
                            removed, pos = removed + reach - begin, reach
                    left.append(data[pos:])
                    rows.append((doc_id, len(data), removed, n_spans, b"".join(left)))
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")

