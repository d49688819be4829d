"""Language identification by a blended-spectrum string kernel with Nystroem landmarks and kernel ridge regression.

The kernel of two texts is the number of byte n-grams (n from 1 to 3, ASCII letters lower-cased) present in both, divided by the
root of the product of the numbers present in each. Landmark texts fix the n-grams that count. A text's kernel values with all landmarks
come from one product of its presence row with the landmarks' rows; the Nystroem map whitens them and one ridge
regression per language against the rest scores them. Because the kernel is linear in the presence rows, landmark
rows, whitening and weights are multiplied once when the model is fitted, and a batch needs a single matrix product.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.llm import samples
from coloc.llm.ragged import flat, slices
from coloc.llm.tables import narrow, ship

SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"
UNKNOWN = "und"
#: Bounds of the training sample: distinct texts of a language, pieces of a long text, characters of a piece; landmarks of a language.
QUOTA, PIECES, PIECE, LANDMARKS = 300, 2, 16_384, 24
#: Digits of a margin that count: a matrix product may round the rest by a row's place in its batch.
DIGITS = 4
RIDGE, SHARPNESS = 0.1, 6.0
DIVISOR, HELD_OUT = 3, 1
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = True


@dataclass
class Model:
    languages: list[str]
    alphabet: np.ndarray  # bytes of the landmarks
    grams: np.ndarray  # codes of their n-grams, ascending
    weights: np.ndarray  # n-grams x languages


class Grams:
    """Columns of the n-grams that occur in a text, by tables over a small alphabet."""

    def __init__(self, alphabet: np.ndarray, grams: np.ndarray):
        self.size = len(alphabet) + 1
        self.symbol = np.zeros(256, np.int32)
        self.symbol[alphabet] = np.arange(1, self.size)
        self.column = np.full(self.size**3, len(grams), np.int32)
        self.column[grams] = np.arange(len(grams))
        self.width = len(grams)

    def codes(self, raw: np.ndarray, first: np.ndarray) -> Iterator[np.ndarray]:
        """For n = 1, 2, 3 the code of the n-gram that ends at each byte; 0 where it would begin in the text before."""
        s = self.symbol[_LOWER[raw]]
        yield s
        two = np.zeros_like(s)
        two[1:] = np.where((s[1:] > 0) & (s[:-1] > 0) & ~first[1:], s[:-1] * self.size + s[1:], 0)
        yield two
        three = np.zeros_like(s)
        three[2:] = np.where((two[2:] > 0) & (two[1:-1] > 0), s[:-2] * self.size**2 + two[2:], 0)
        yield three

    def presence(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Rows of 0 and 1 for the documents."""
        n = len(offsets) - 1
        first = np.zeros(len(raw) + 1, bool)
        first[offsets[:-1]] = True
        columns = [self.column.take(code) for code in self.codes(raw, first[:-1])]
        out = np.zeros((n, self.width + 1), np.float32)  # the spare last column takes all others
        for row, a, b in zip(out, offsets[:-1].tolist(), offsets[1:].tolist()):
            for column in columns:
                row[column[a:b]] = 1
        return out[:, : self.width]


def fit(rows: list[tuple[str, str]]) -> Model:
    """A model of (language, text) rows, of which the first LANDMARKS of each language are the landmarks."""
    languages = sorted({r[0] for r in rows})
    if not languages:
        return Model([], np.zeros(0, np.uint8), np.zeros(0, np.int64), np.zeros((0, 0), np.float32))
    marks = [t for lang in languages for t in [r[1] for r in rows if r[0] == lang][:LANDMARKS]]
    raw, offsets = flat(pa.array(marks))
    alphabet = np.unique(_LOWER[raw])
    every = Grams(alphabet, np.zeros(0, np.int64))
    first = np.zeros(len(raw) + 1, bool)
    first[offsets[:-1]] = True
    grams = np.unique(np.concatenate([c[c > 0] for c in every.codes(raw, first[:-1])]))
    table = Grams(alphabet, grams)
    land = table.presence(raw, offsets)
    land /= np.sqrt(np.maximum(land.sum(1, keepdims=True), 1))
    phi, want = [], []
    for i in range(0, len(rows), 200):
        some = rows[i : i + 200]
        x = table.presence(*flat(pa.array([t for _, t in some])))
        phi.append(x / np.sqrt(np.maximum(x.sum(1, keepdims=True), 1)) @ land.T)
        want += [languages.index(lang) for lang, _ in some]
    k = np.concatenate(phi).astype(np.float64)
    values, vectors = np.linalg.eigh((land @ land.T).astype(np.float64))
    good = values > 1e-6 * values.max()
    white = vectors[:, good] / np.sqrt(values[good])
    z = k @ white
    y = np.where(np.arange(len(languages)) == np.array(want)[:, None], 1.0, -1.0)
    ridge = np.linalg.solve(z.T @ z + RIDGE * np.eye(z.shape[1]), z.T @ y)
    return Model(languages, alphabet, grams, (land.T.astype(np.float64) @ (white @ ridge)).astype(np.float32))


def _has_letter(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    run = np.append(0, np.cumsum(_LETTER[raw]))
    out = run[offsets[1:]] > run[offsets[:-1]]
    for i in np.flatnonzero(~out & (offsets[1:] > offsets[:-1])).tolist():
        out[i] = any(c.isalpha() for c in raw[offsets[i] : offsets[i + 1]].tobytes().decode("utf-8", "replace"))
    return out


def predict(model: Model, grams: Grams, raw: np.ndarray, offsets: np.ndarray) -> tuple[list[str], np.ndarray]:
    n = len(offsets) - 1
    letters = _has_letter(raw, offsets)
    score = np.zeros(n)
    best = np.zeros(n, np.int64)
    if model.languages:
        step = max(1, 4_000_000 // max(1, grams.width))
        for i in range(0, n, step):
            at = offsets[i : min(n, i + step) + 1]
            x = grams.presence(raw[at[0] : at[-1]], at - at[0])
            margin = np.round(((x @ model.weights) / np.sqrt(np.maximum(x.sum(1, keepdims=True), 1))).astype(np.float64), DIGITS)
            e = np.exp(SHARPNESS * (margin - margin.max(1, keepdims=True)))
            part = slice(i, i + len(x))
            best[part], score[part] = margin.argmax(1), (e / e.sum(1, keepdims=True)).max(1)
    named = [model.languages[b] if ok and model.languages else UNKNOWN for b, ok in zip(best.tolist(), letters.tolist())]
    return named, np.where(letters, score, 0.0)


def _predicted(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    grams = Grams(model.alphabet, model.grams)
    for batch in slices(batches, 2, 4_000_000):
        lang, score = predict(model, grams, *flat(batch.column(2)))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(lang, pa.string()), pa.array(score)], ["doc_id", "held_out", "lang_pred", "score"])


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Fits on at most QUOTA distinct texts of each language, those with the smallest hashes, from rows outside the held-out fold."""
    rows = narrow(docs, doc_id=id_col, text=text_col, lang=lang_col).where(samples.remainder("doc_id", DIVISOR) != HELD_OUT)
    return fit(samples.per_class(rows, "lang", "text", QUOTA, PIECES, PIECE))


def languages(docs: DataFrame, model: Model | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row, from its whole text of any length.

    A null text, or one without a letter (also an empty one), gets UNKNOWN and score 0; so do all rows if no labelled text is there to
    learn from. Ties go to the language first in order. A null id counts as empty text in the fold's checksum; repeated
    rows each give a row, an empty table none, other columns are ignored.
    """
    ship(docs.sparkSession)
    model = model or train(docs, id_col, text_col, lang_col)
    rows = narrow(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), (samples.remainder("doc_id", DIVISOR) == HELD_OUT).alias("held_out"), "text")
    return rows.mapInArrow(partial(_predicted, model=model), SCHEMA)


def _accepted(batches: Iterator[pa.RecordBatch], model: Model, text: int, least: float) -> Iterator[pa.RecordBatch]:
    grams = Grams(model.alphabet, model.grams)
    for batch in slices(batches, text, 4_000_000):
        lang, score = predict(model, grams, *flat(batch.column(text)))
        yield batch.filter(pa.array([name != UNKNOWN and s >= least for name, s in zip(lang, score.tolist())], pa.bool_()))


def accepted(docs: DataFrame, least: float = 0.3, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The rows of docs, with all their columns, whose language is known with at least that score.

    Null, empty and letterless texts have no known language and go, as do all rows if no row has a language to learn from. Equal rows are kept
    or dropped together, an empty table stays empty, and null ids and clashing other columns make no difference.
    """
    ship(docs.sparkSession)
    model = train(docs, id_col, text_col, lang_col)
    return docs.mapInArrow(partial(_accepted, model=model, text=docs.columns.index(text_col), least=least), docs.schema)
