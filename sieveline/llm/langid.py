"""Language identification by hyperdimensional profiles (operator 3).

Every letter has a random vector of +1 and -1, derived from its code point. A trigram is
bound from its letters' vectors, each rotated by its place, by multiplication; a text is
the bundle (sum) of its trigrams, and a language the bundle of its training texts. A text
gets the language whose prototype has the largest cosine with it. Before comparison the
mean of the prototypes, which all languages share, is projected out of both sides.

Bundles are integer sums, so that neither the order of rows nor the number of tasks moves
a result. A task emits one vector per language; the driver gets a prototype per language.

Defined results: null text, or text without a letter, is ``und`` with score 0, and so is
any text when nothing was learnt. Ties go to the first language by code point. Rows are
judged alone; repeated rows weigh twice in training. Rows with a null language, or a null
id under :func:`split`, are not learnt from.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import stepwise

#: Length of the vectors and letters per n-gram.
DIMENSIONS, N = 1024, 3
#: Rows of n-gram vectors that a worker remembers.
REMEMBERED = 30_000


class Encoder:
    """Letters to n-gram codes to vectors; all derived from code points."""

    def __init__(self):
        self.letters: dict[int, np.ndarray] = {}
        self.rows: dict[int, int] = {}
        self.table = np.empty((REMEMBERED, DIMENSIONS), np.int8)

    def letter(self, cp: int) -> np.ndarray:
        if cp not in self.letters:
            bits = np.random.Generator(np.random.Philox(key=cp + 1)).integers(0, 2, DIMENSIONS, np.int8)
            self.letters[cp] = bits * np.int8(2) - np.int8(1)
        return self.letters[cp]

    @staticmethod
    def codes(text: str) -> tuple[np.ndarray, np.ndarray]:
        """Distinct trigram codes of a text and their counts; none where it has no letter."""
        low = text.lower()
        cps = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), np.uint32)
        present = np.unique(cps)
        letters = present[[chr(c).isalpha() for c in present.tolist()]]
        if not len(letters):
            return np.empty(0, np.int64), np.empty(0, np.int64)
        cps = np.where(np.isin(cps, letters), cps, 32).astype(np.int64)
        cps = np.concatenate([[32], cps, [32]])
        cps = cps[np.concatenate([[True], (cps[1:] != 32) | (cps[:-1] != 32)])]
        grams = (cps[:-2] << 42) | (cps[1:-1] << 21) | cps[2:]
        return np.unique(grams, return_counts=True)

    def vector(self, text: str | None) -> np.ndarray | None:
        """The bundle of a text's trigrams, or None without a letter."""
        grams, counts = self.codes(text or "")
        if not len(grams):
            return None
        total = np.zeros(DIMENSIONS, np.int64)
        for at in range(0, len(grams), 4096):
            rows = self.table[self._rows(grams[at : at + 4096].tolist())].astype(np.float32)
            # Sums stay under 2**24 in a step unless one text has millions of words; then go by float64.
            part = counts[at : at + 4096]
            kind = np.float32 if part.sum() < 1 << 24 else np.float64
            total += np.rint(part.astype(kind) @ rows.astype(kind, copy=False)).astype(np.int64)
        return total

    def _rows(self, grams: list[int]) -> list[int]:
        if len(self.rows) + len(grams) > REMEMBERED:
            self.rows.clear()
        for g in grams:
            if g not in self.rows:
                mask = (1 << 21) - 1
                a, b, c = (self.letter(g >> s & mask) for s in (42, 21, 0))
                self.table[len(self.rows)] = np.roll(a, 2) * np.roll(b, 1) * c
                self.rows[g] = len(self.rows)
        return [self.rows[g] for g in grams]


def split(id_col: Column) -> Column:
    """Whether an id is held out of training: crc32 of its text leaves 1 modulo 3."""
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def learn(labelled: DataFrame, text_col: str = "text", lang_col: str = "lang") -> dict[str, list[int]]:
    """A prototype per language, bundled over all rows with a language."""

    def run(batches):
        enc, sums = Encoder(), {}
        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1)):
                v = enc.vector(text.as_py())
                if v is not None:
                    sums[lang.as_py()] = sums.get(lang.as_py(), 0) + v
        for lang, v in sums.items():
            yield pa.RecordBatch.from_pydict({"lang": [lang] * DIMENSIONS, "d": pa.array(range(DIMENSIONS), pa.int32()), "v": v})

    rows = labelled.filter(F.col(lang_col).isNotNull()).select(F.col(text_col).cast("string"), F.col(lang_col).cast("string"))
    sums = rows.mapInArrow(stepwise(run), "lang string, d int, v long").groupBy("lang", "d").agg(F.sum("v").alias("v"))
    model: dict[str, list[int]] = {}
    for r in sums.collect():  # languages x DIMENSIONS rows
        model.setdefault(r.lang, [0] * DIMENSIONS)[r.d] = r.v
    return dict(sorted(model.items()))


def _unit(m: np.ndarray) -> np.ndarray:
    norm = np.linalg.norm(m, axis=-1, keepdims=True)
    return m / np.where(norm > 0, norm, 1)


def identify(df: DataFrame, model: dict[str, list[int]], text_col: str = "text", lang_out: str = "lang_pred", score_out: str = "score") -> DataFrame:
    """Add the predicted language and a score from 0 to 1 (half of one plus the cosine)."""
    keep = [c for c in df.columns if c not in (lang_out, score_out)]
    # A text that is kept anyway is not sent to the worker twice.
    own = text_col in keep and df.schema[text_col].dataType == T.StringType()
    at = keep.index(text_col) if own else len(keep)
    names = list(model)
    vectors = _unit(np.array([model[k] for k in names], np.float64).reshape(len(names), DIMENSIONS))
    shared = _unit(vectors.mean(axis=0, keepdims=True))[0] if len(names) > 1 else np.zeros(DIMENSIONS)
    protos = _unit(vectors - np.outer(vectors @ shared, shared))

    def run(batches):
        enc = Encoder()
        for batch in batches:
            langs, scores = [], []
            for text in batch.column(at):
                v = enc.vector(text.as_py()) if names else None
                if v is None:
                    langs.append("und")
                    scores.append(0.0)
                    continue
                x = _unit(v.astype(np.float64))
                cos = protos @ _unit(x - (x @ shared) * shared)
                best = int(np.argmax(cos))
                langs.append(names[best])
                scores.append(float(min(1.0, max(0.0, (1 + cos[best]) / 2))))
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(keep))), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[*keep, lang_out, score_out])

    kept = df.select(*[F.col(f"`{c}`") for c in keep])
    source = kept if own else df.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`").cast("string").alias("__text"))
    schema = T.StructType([*kept.schema.fields, T.StructField(lang_out, T.StringType()), T.StructField(score_out, T.DoubleType())])
    return source.mapInArrow(stepwise(run), schema)
