"""Language identification by a byte convolutional network trained in numpy.

Filters of widths 2, 3 and 4 run over lower-cased bytes of a fixed-length window, each filter keeps its largest response, and
a softmax over these gives the window's languages. A text is cut into windows that overlap by three bytes and cover all of
it; its score is the mean of its windows' probabilities, weighted by their bytes. For inference the filter of each
width is summed into tables of byte pairs, which gives the same responses with fewer look-ups.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, materialize

WIDTHS = (2, 3, 4)
FILTERS = 16
WINDOW = 256
OVERLAP = max(WIDTHS) - 1
#: The training sample, the one bound on what is learned from: rows a language, rows in all (shared evenly if the languages
#: are many), and pieces of each row's text.
MOST_ROWS, SAMPLE_ROWS, PIECES, PIECE_CHARS = 400, 50_000, 4, 200
#: Steps of training: so many for up to eight languages, and in proportion for more.
STEPS, STEPS_UPTO, BATCH, RATE = 500, 8, 128, 0.01
#: Windows held at once in a worker: about 16 MB a table look-up.
CHUNK = 1024
NO_LANGUAGE = "und"

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def windows_of(text: str, size: int = WINDOW) -> np.ndarray:
    """A text's windows as rows of bytes, the last one padded with zeros."""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass").translate(_LOWER), dtype=np.uint8)
    step = size - OVERLAP
    m = max(1, -(-(len(raw) - OVERLAP) // step))
    padded = np.zeros(m * step + OVERLAP, dtype=np.uint8)
    padded[: len(raw)] = raw
    return np.lib.stride_tricks.sliding_window_view(padded, size)[::step]


class ByteConvNet:
    """filters[w]: (width, 256, FILTERS); bias, dense and offset of the softmax; languages in the order of its outputs."""

    def __init__(self, languages: list[str], seed: int = 5):
        rng = np.random.default_rng(seed)
        self.languages = languages
        self.filters = [rng.normal(0, 0.3, (w, 256, FILTERS)).astype(np.float32) for w in WIDTHS]
        for f in self.filters:
            f[:, 0, :] = 0  # padding
        self.bias = np.zeros(len(WIDTHS) * FILTERS, dtype=np.float32)
        self.dense = rng.normal(0, 0.1, (len(WIDTHS) * FILTERS, len(languages))).astype(np.float32)
        self.offset = np.zeros(len(languages), dtype=np.float32)

    def _respond(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Largest response and its place, of every window and filter, straight from the filters."""
        best, place = [], []
        for f in self.filters:
            n = x.shape[1] - len(f) + 1
            z = sum(f[o][x[:, o : o + n]] for o in range(len(f)))
            at = z.argmax(axis=1)
            place.append(at)
            best.append(np.take_along_axis(z, at[:, None, :], axis=1)[:, 0])
        return np.concatenate(best, axis=1), np.concatenate(place, axis=1)

    def fit(self, x: np.ndarray, y: np.ndarray, steps: int = STEPS, seed: int = 5) -> ByteConvNet:
        """Adam on the cross entropy; a filter's gradient reaches only the bytes of its largest response."""
        rng = np.random.default_rng(seed)
        params = [*self.filters, self.bias, self.dense, self.offset]
        first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        for step in range(1, steps + 1):
            rows = rng.integers(0, len(x), BATCH)
            xb, yb = x[rows], y[rows]
            pooled, place = self._respond(xb)
            hidden = np.maximum(pooled + self.bias, 0)
            error = softmax(hidden @ self.dense + self.offset)
            error[np.arange(BATCH), yb] -= 1
            error /= BATCH
            back = (error @ self.dense.T) * (hidden > 0)
            grads = [np.zeros_like(p) for p in params]
            for k, f in enumerate(self.filters):
                part = slice(k * FILTERS, (k + 1) * FILTERS)
                columns = np.broadcast_to(np.arange(FILTERS), (BATCH, FILTERS))
                for o in range(len(f)):
                    np.add.at(grads[k][o], (np.take_along_axis(xb, place[:, part] + o, axis=1), columns), back[:, part])
                grads[k][:, 0, :] = 0
            grads[-3], grads[-2], grads[-1] = back.sum(0), hidden.T @ error, error.sum(0)
            for p, g, m, v in zip(params, grads, first, second, strict=True):
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                p -= RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        return self

    def tables(self) -> list[tuple[np.ndarray, ...]]:
        """Per width the tables by byte pair, and for an odd width the last byte's."""
        out = []
        for f in self.filters:
            pairs = [(f[o][:, None, :] + f[o + 1][None, :, :]).reshape(1 << 16, FILTERS) for o in range(0, len(f) - 1, 2)]
            out.append((*pairs, *([f[-1]] if len(f) % 2 else [])))
        return out

    def probabilities(self, x: np.ndarray, tables: list[tuple[np.ndarray, ...]]) -> np.ndarray:
        """Softmax of every window, in chunks of bounded size."""
        out = np.empty((len(x), len(self.languages)), dtype=np.float32)
        for a in range(0, len(x), CHUNK):
            part = x[a : a + CHUNK]
            pair = part[:, :-1].astype(np.int32) * 256 + part[:, 1:]
            pooled = []
            for (*twos, last), w in zip(tables, WIDTHS, strict=True):
                if w % 2 == 0:
                    twos = [*twos, last]
                n = part.shape[1] - w + 1
                z = twos[0].take(pair[:, :n], axis=0)
                for i, t in enumerate(twos[1:], 1):
                    z += t.take(pair[:, 2 * i : 2 * i + n], axis=0)
                if w % 2:
                    z += last.take(part[:, w - 1 : w - 1 + n], axis=0)
                pooled.append(z.max(axis=1))
            hidden = np.maximum(np.concatenate(pooled, axis=1) + self.bias, 0)
            out[a : a + CHUNK] = softmax(hidden @ self.dense + self.offset)
        return out


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def training_sample(rows: DataFrame, sample_rows: int = SAMPLE_ROWS) -> list[tuple[str, str]]:
    """(language, piece of text): PIECES pieces of about MOST_ROWS rows of each language, or of fewer if there are so many languages that
    these come to more than sample_rows.

    rows: doc_id, text, lang. Rows are drawn by a hash of the id at the rate that each language's count asks for; every language is
    learned, unless there are more of them than sample_rows.
    """
    usable = rows.where("lang is not null and text is not null and char_length(text) > 0")
    counts = materialize(usable.groupBy(F.col("lang").alias("_lang")).agg(F.count(F.lit(1)).alias("_n")), "language-counts")
    languages = counts.count()
    if not languages:
        return []
    each = max(1, min(MOST_ROWS, sample_rows // languages))
    draw = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1 << 30)) / float(1 << 30)
    # rows that no language could draw do not meet the join; a language of few rows gives all it has
    least = counts.agg(F.min("_n")).first()[0]
    chosen = usable.where(draw < min(1.0, each / least)).join(counts, F.col("lang") == F.col("_lang")).where(draw < F.lit(float(each)) / F.col("_n"))
    room = F.greatest(F.char_length("text") - PIECE_CHARS, F.lit(0)) + 1
    pieces = [F.substring(F.col("text"), (F.pmod(F.xxhash64("doc_id", F.lit(20 + i)), room) + 1).cast("int"), F.lit(PIECE_CHARS)) for i in range(PIECES)]
    taken = chosen.select("lang", F.xxhash64("doc_id").alias("h"), F.array(*pieces).alias("pieces")).orderBy("h").limit(2 * sample_rows).collect()
    return [(r["lang"], p) for r in taken for p in r["pieces"]]


def train(sample: list[tuple[str, str]], seed: int = 5) -> ByteConvNet | None:
    """A network for the sample's languages, each with the same weight in training; None for an empty sample."""
    languages = sorted({k for k, _ in sample})
    if not languages:
        return None
    by = [np.concatenate([windows_of(p)[:1] for k, p in sample if k == name]) for name in languages]
    most = max(map(len, by))
    rng = np.random.default_rng(seed)
    x = np.concatenate([b[rng.permutation(np.arange(most) % len(b))] for b in by])
    steps = STEPS * max(1, -(-len(languages) // STEPS_UPTO))
    return ByteConvNet(languages, seed).fit(x, np.repeat(np.arange(len(languages)), most), steps)


RESULT = "doc_id long, held_out boolean, lang_pred string, score double"


def identify(docs: DataFrame, net: ByteConvNet | None, held_out, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row; a null text, one without a letter, or no network at all gives `und` and 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = net.tables() if net else []
        for b in batches:
            n = b.num_rows
            names, scores = [NO_LANGUAGE] * n, [0.0] * n
            waiting: list[tuple[int, np.ndarray, int]] = []
            held = 0

            def settle() -> None:
                if not waiting:
                    return
                p = net.probabilities(np.concatenate([w for _, w, _ in waiting]), tables)
                at = 0
                for i, w, size in waiting:
                    part = p[at : at + len(w)]
                    at += len(w)
                    weight = np.full(len(w), WINDOW - OVERLAP, dtype=np.float64)
                    weight[-1] = max(1, size - (len(w) - 1) * (WINDOW - OVERLAP))
                    mean = weight @ part / weight.sum()
                    k = int(mean.argmax())
                    names[i], scores[i] = net.languages[k], min(1.0, float(mean[k]))
                waiting.clear()

            for i, text in enumerate(b.column(2)):
                t = text.as_py()
                if not net or not t or not any(c.isalpha() for c in t):
                    continue
                w = windows_of(t)
                waiting.append((i, w, len(t.encode("utf-8", "surrogatepass"))))
                held += len(w)
                if held >= 4 * CHUNK:
                    settle()
                    held = 0
            settle()
            yield pa.record_batch([b.column(0), b.column(1), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out.alias("held_out"), F.col(text_col).alias("text")).mapInArrow(lean(run), RESULT)


def language_id(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Trains on text and non-null language of rows whose crc32 of the id as text is not 1 mod 3, and predicts all rows.

    A null id is neither trained on nor held out. Rows that repeat an id get the same held_out. Every language is
    learned, one of few rows from those. Whole texts are read, however long. An empty table gives an empty result.
    """
    third = F.crc32(F.col(id_col).cast("string").cast("binary")) % 3
    seen = docs.where(third != 1).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang"))
    return identify(docs, train(training_sample(seen)), F.coalesce(third == 1, F.lit(False)), id_col, text_col)
