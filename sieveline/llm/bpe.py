"""Byte-level BPE encoding and decoding (operator 10) on a sentencepiece runtime.

The rank file of a byte-level vocabulary becomes a sentencepiece BPE model without any
training: :func:`model_proto` writes the protocol-buffer message itself. Each token's bytes
are mapped to one printable character a byte, its score is its negative rank, so that the
runtime's best-score merge is the lowest-rank merge, and normalisation is the identity.
Text is cut into pre-tokens by a pattern; each distinct part of a batch between blanks is
cut and encoded once. Decoding looks the bytes of
each id up, again one ``take`` a batch. Where the pattern does not cut before every lone blank
(:func:`cuts_before_blanks`), whole texts are cut instead.

A pre-token that is itself in the vocabulary is that one id, as rank-based encoders have it.

Defined results: null text is an empty one (no ids, no bytes); unknown ids fail; an empty
table gives an empty one; other columns are carried along unless their names clash with
the new column, which then replaces them.
"""

from __future__ import annotations

import base64
import struct
from array import array
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import stepwise

#: Text that one step of the encoder holds as Python strings.
STEP_CHARS = 1 << 19
#: Distinct parts between blanks in each of the two generations that a worker remembers.
REMEMBERED = 80_000


def byte_chars() -> list[str]:
    """A printable character for each byte: itself where it is printable in Latin-1, else from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    moved = iter(range(0x100, 0x200))
    return [chr(b if b in plain else next(moved)) for b in range(256)]


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes(out + bytes([n]))


def _field(number: int, value: int | float | bytes | str) -> bytes:
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    if isinstance(value, int):
        return _varint(number << 3) + _varint(value)
    value = value.encode() if isinstance(value, str) else value
    return _varint(number << 3 | 2) + _varint(len(value)) + value


def model_proto(ranks: dict[bytes, int]) -> tuple[bytes, list[int]]:
    """A serialised sentencepiece BPE model and, for each of its piece ids, the vocabulary's id."""
    chars = byte_chars()
    order = sorted(ranks, key=ranks.get)
    # Field numbers and enum values of the public sentencepiece message format.
    unknown = _field(1, "<unk>") + _field(2, 0.0) + _field(3, 2)
    pieces = [_field(1, unknown)]
    pieces += [_field(1, _field(1, "".join(chars[b] for b in token)) + _field(2, -float(ranks[token])) + _field(3, 1)) for token in order]
    trainer = _field(3, 2) + _field(4, len(pieces)) + _field(40, 0) + _field(41, -1 & (1 << 64) - 1) + _field(42, -1 & (1 << 64) - 1) + _field(43, -1 & (1 << 64) - 1)
    normaliser = _field(1, "identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)
    return b"".join(pieces) + _field(2, trainer) + _field(3, normaliser), [-1, *(ranks[t] for t in order)]


def cuts_before_blanks(find) -> bool:
    """Whether a blank between two other characters always starts a pre-token, as probes of all kinds of neighbours show."""
    kinds = ["a", "Z", "é", "日", "ß", "7", "½", ".", "'", "'s", "_", "-", "😀", "\u0301", "\x00", "ab12", "!?", "$"]
    return all(find(f"{x} {y}") == [*find(x), *find(f" {y}")] and "".join(find(f"{x} {y}")) == f"{x} {y}" for x in kinds for y in kinds)


class ByteBpe:
    """Encoder of one vocabulary."""

    def __init__(self, path: str, pattern: str):
        import sentencepiece

        ranks = read_ranks(path)
        proto, self.ids = model_proto(ranks)
        self.model = sentencepiece.SentencePieceProcessor(model_proto=proto)
        self.at = {token: i for i, token in enumerate(sorted(ranks, key=ranks.get), 1)}
        self.ids = pa.array(self.ids, pa.int32())
        self.chars = dict(enumerate(byte_chars()))
        self.find = regex.compile(pattern).findall
        self.by_parts = cuts_before_blanks(self.find)
        self.known: dict[str, bytes | None] = {}
        self.older: dict[str, bytes | None] = {}

    def _code(self, text: str) -> bytes:
        """Packed runtime ids of a text, pre-token by pre-token."""
        out = array("i")
        for t in self.find(text):
            raw = t.encode("utf-8", "surrogatepass")
            own = self.at.get(raw)
            if own is None:
                out.extend(self.model.encode(raw.decode("latin-1").translate(self.chars)))
            else:
                out.append(own)
        return out.tobytes()

    def _learn(self, parts: set[str]) -> None:
        """Have in ``known`` the packed ids of each part with a blank before it.

        A lone blank between other characters always starts a pre-token, so what lies
        between two of them is encoded alone. Parts that white space borders are marked
        by None: texts with them are encoded as a whole.
        """
        if len(self.known) > REMEMBERED:
            self.known, self.older = {}, self.known
        known, older, at, chars = self.known, self.older, self.at, self.chars
        new, tokens, coded = [], [], []
        for part in parts.difference(known):
            if (ids := older.get(part)) is not None:
                known[part] = ids
            elif not part or part[0].isspace() or part[-1].isspace():
                known[part] = None
            else:
                found = self.find(" " + part)
                new.append((part, len(found)))
                tokens += found
        rest = []
        for i, t in enumerate(tokens):
            own = at.get(raw := t.encode("utf-8", "surrogatepass"))
            coded.append(own and own.to_bytes(4, "little"))
            if own is None:
                rest.append((i, raw.decode("latin-1").translate(chars)))
        if rest:
            for (i, _), ids in zip(rest, self.model.encode([x for _, x in rest], num_threads=1)):
                coded[i] = array("i", ids).tobytes()
        k = 0
        for part, n in new:
            known[part] = coded[k] if n == 1 else b"".join(coded[k : k + n])
            k += n

    def encode(self, texts: list[str]) -> pa.ListArray:
        """Ids of each text."""
        cut = [text.split(" ") if self.by_parts else [text] for text in texts]
        self._learn({part for parts in cut for part in parts[1:]})
        known, out = self.known.__getitem__, []
        for text, parts in zip(texts, cut):
            packed = list(map(known, parts[1:]))
            if None in packed or not parts[0] or parts[0][-1].isspace():
                out.append(self._code(text))
            else:
                out.append(self._code(parts[0]) + b"".join(packed))
        flat = self.ids.take(pa.Array.from_buffers(pa.int32(), sum(map(len, out)) // 4, [None, pa.py_buffer(b"".join(out))]))
        ends = pa.array(accumulate((len(x) // 4 for x in out), initial=0), pa.int32())
        return pa.ListArray.from_arrays(ends, flat)


class Pieces:
    """Decoder of one vocabulary: the bytes of each id, without an encoder's runtime."""

    def __init__(self, path: str):
        ranks = read_ranks(path)
        by_id: list[bytes | None] = [None] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            by_id[rank] = token
        self.pieces = pa.array(by_id, pa.large_binary())

    def decode(self, ids: pa.ListArray) -> pa.LargeBinaryArray:
        """Bytes of each list of ids; one contiguous lookup for the batch."""
        flat = self.pieces.take(ids.flatten())
        if flat.null_count:
            raise ValueError("an id is not in the vocabulary")
        cuts = pc.subtract(ids.offsets, ids.offsets[0])
        starts = pa.Array.from_buffers(pa.int64(), len(flat) + 1, [None, flat.buffers()[1]], offset=flat.offset).take(cuts)
        return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(ids), [None, starts.buffers()[1], flat.buffers()[2]])


_loaded: dict[tuple[str, str], ByteBpe] = {}
_pieces: dict[str, Pieces] = {}


def codec(path: str, pattern: str) -> ByteBpe:
    """The worker's encoder, built once from the vocabulary file (same path on every machine)."""
    if (path, pattern) not in _loaded:
        _loaded[path, pattern] = ByteBpe(path, pattern)
    return _loaded[path, pattern]


def pieces(path: str) -> Pieces:
    """The worker's decoder, likewise."""
    if path not in _pieces:
        _pieces[path] = Pieces(path)
    return _pieces[path]


def _slices(column: pa.Array, most: int, sizes: pa.Array) -> Iterator[tuple[int, int]]:
    start = held = 0
    for i, n in enumerate(sizes.to_pylist()):
        if held and held + n > most:
            yield start, i - start
            start, held = i, 0
        held += n or 1
    if start < len(column):
        yield start, len(column) - start


def encode(df: DataFrame, path: str, pattern: str, text_col: str = "text", ids_col: str = "ids") -> DataFrame:
    """Add ``ids_col`` (array<int>): the ids of each whole text."""
    keep = [c for c in df.columns if c != ids_col]
    # A text that is kept anyway is not sent to the worker twice.
    own = text_col in keep and df.schema[text_col].dataType == T.StringType()
    at = keep.index(text_col) if own else len(keep)

    def run(batches):
        bpe = codec(path, pattern)
        for batch in batches:
            texts = batch.column(at).cast(pa.string())
            sizes = pc.fill_null(pc.binary_length(texts), 0)
            for start, n in _slices(texts, STEP_CHARS, sizes):
                part = batch.slice(start, n)
                ids = bpe.encode([x or "" for x in texts.slice(start, n).to_pylist()])
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), ids], names=[*keep, ids_col])

    sent = [] if own else [F.col(f"`{text_col}`").cast("string").alias("__text")]
    source = df.select(*[F.col(f"`{c}`") for c in keep], *sent)
    schema = T.StructType([*(df.schema[c] for c in keep), T.StructField(ids_col, T.ArrayType(T.IntegerType()))])
    return source.mapInArrow(stepwise(run), schema)


def decode(df: DataFrame, path: str, pattern: str, ids_col: str = "ids", bytes_col: str = "decoded") -> DataFrame:
    """Add ``bytes_col`` (binary): the bytes that each list of ids stands for (null list: empty)."""
    keep = [c for c in df.columns if c != bytes_col]

    def run(batches):
        bpe = pieces(path)
        for batch in batches:
            ids = batch.column(len(keep))
            sizes = pc.fill_null(pc.list_value_length(ids), 0)
            for start, n in _slices(ids, STEP_CHARS, sizes):
                part = pa.concat_arrays([ids.slice(start, n)])
                raw = bpe.decode(part)
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(start, n) for i in range(len(keep))), raw.cast(pa.binary())], names=[*keep, bytes_col])

    ids = F.coalesce(F.col(f"`{ids_col}`"), F.array().cast("array<int>")).alias("__ids")
    schema = T.StructType([*(df.schema[c] for c in keep), T.StructField(bytes_col, T.BinaryType())])
    return df.select(*[F.col(f"`{c}`") for c in keep], ids).mapInArrow(stepwise(run), schema)


def round_trip(df: DataFrame, path: str, pattern: str, text_col: str = "text", ids_col: str = "ids", bytes_col: str = "decoded") -> DataFrame:
    """Ids of each whole text and the bytes that these ids stand for, in one worker; the text itself goes.

    The same as :func:`decode` of :func:`encode`, without a second worker and a way of the ids through the JVM.
    """
    keep = [c for c in df.columns if c not in (text_col, ids_col, bytes_col)]

    def run(batches):
        coder, decoder = codec(path, pattern), pieces(path)
        for batch in batches:
            texts = batch.column(len(keep)).cast(pa.string())
            for start, n in _slices(texts, STEP_CHARS, pc.fill_null(pc.binary_length(texts), 0)):
                ids = coder.encode([x or "" for x in texts.slice(start, n).to_pylist()])
                raw = decoder.decode(ids).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(start, n) for i in range(len(keep))), ids, raw], names=[*keep, ids_col, bytes_col])

    source = df.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`").cast("string").alias("__text"))
    schema = T.StructType([*(df.schema[c] for c in keep), T.StructField(ids_col, T.ArrayType(T.IntegerType())), T.StructField(bytes_col, T.BinaryType())])
    return source.mapInArrow(stepwise(run), schema)


def digests(df: DataFrame, ids_col: str = "ids", bytes_col: str = "decoded", id_col: str = "doc_id") -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of encoded and decoded rows."""
    listed = F.array_join(F.transform(ids_col, lambda x: x.cast("string")), ",")
    return df.select(id_col, F.size(ids_col).cast("long").alias("n_tokens"), F.sha2(listed.cast("binary"), 256).alias("ids_sha256"), F.sha2(F.col(bytes_col), 256).alias("decoded_sha256"))
