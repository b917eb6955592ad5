"""Language identification by a byte convolutional network, trained in numpy.

Texts are cut into fixed windows of bytes.  Filters of several widths slide over
each window, the strongest response of each filter is kept (max pooling), and a
softmax layer over those gives the window's languages.  A text is scored by the
mean of its windows' log-probabilities, over all its windows.

Bytes are one-hot classes (A-Z folded to a-z, digits together), so a filter of
width w is a sum of w table rows; pairs of neighbouring bytes share one table
lookup when the trained network is applied.

Training uses a bounded sample of labelled documents, the ``per_language``
smallest of a hash of the document, and ``windows`` windows of each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .textbits import slices, text_view

WINDOW = 256
WIDTHS = (2, 3, 4)
FILTERS = 8
UNKNOWN = "und"
#: Bounds of the training sample; more languages raise an error.
PER_LANGUAGE, WINDOWS, MOST_LANGUAGES = 600, 4, 1000
#: Bytes that the network is applied to at a time, a whole number of windows.
BLOCK_BYTES = 128 * WINDOW


def _classes() -> np.ndarray:
    """Class of each byte; 0 pads and stands for all control bytes."""
    out = np.zeros(256, np.int64)
    out[[9, 10, 11, 12, 13, 32]] = 1
    out[48:58] = 2
    out[33:48] = out[58:65] = out[91:97] = out[123:127] = 3
    out[97:123] = np.arange(4, 30)
    out[65:91] = np.arange(4, 30)
    out[128:] = np.arange(30, 158)
    return out


CLASS = _classes().astype(np.int16)
CLASSES = 158


class ByteNet:
    """Tables of filters per width, biases, and the softmax layer."""

    def __init__(self, languages: list[str], seed: int = 11):
        rng = np.random.default_rng(seed)
        self.languages = languages
        self.filters = [rng.normal(0, 0.1, (w, CLASSES, FILTERS)).astype(np.float32) for w in WIDTHS]
        self.bias = np.zeros(FILTERS * len(WIDTHS), np.float32)
        self.out = rng.normal(0, 0.1, (FILTERS * len(WIDTHS), len(languages))).astype(np.float32)
        self.out_bias = np.zeros(len(languages), np.float32)

    def _respond(self, x: np.ndarray) -> list[np.ndarray]:
        """Responses of each width's filters at each place of windows of classes."""
        pair = x[:, :-1].astype(np.int32) * CLASSES + x[:, 1:]
        t2, t3, t4 = self.filters
        n = x.shape[1]
        joint = np.concatenate([(t[0][:, None, :] + t[1][None, :, :]).reshape(-1, FILTERS) for t in (t2, t3, t4)], axis=1) if self._joint is None else self._joint
        late = (t4[2][:, None, :] + t4[3][None, :, :]).reshape(-1, FILTERS) if self._late is None else self._late
        first = joint[pair]
        return [first[:, :, :FILTERS], first[:, : n - 2, FILTERS : 2 * FILTERS] + t3[2][x[:, 2:]], first[:, : n - 3, 2 * FILTERS :] + late[pair[:, 2:]]]

    _joint = _late = None

    def freeze(self) -> "ByteNet":
        """Build the pair tables once, for applying the network."""
        t2, t3, t4 = self.filters
        self._joint = np.concatenate([(t[0][:, None, :] + t[1][None, :, :]).reshape(-1, FILTERS) for t in (t2, t3, t4)], axis=1)
        self._late = np.ascontiguousarray((t4[2][:, None, :] + t4[3][None, :, :]).reshape(-1, FILTERS))
        return self

    def log_probabilities(self, x: np.ndarray) -> np.ndarray:
        pooled = np.concatenate([r.max(axis=1) for r in self._respond(x)], axis=1)
        z = np.maximum(pooled + self.bias, 0) @ self.out + self.out_bias
        z -= z.max(axis=1, keepdims=True)
        return z - np.log(np.exp(z).sum(axis=1, keepdims=True))

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 14, batch: int = 64, rate: float = 0.01, seed: int = 5) -> None:
        """Adam on the cross-entropy; the max pool passes gradients to one place."""
        rng = np.random.default_rng(seed)
        params = [*self.filters, self.bias, self.out, self.out_bias]
        mean, square, step = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
        k = np.arange(FILTERS)
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(x), batch):
                xb, yb = x[order[at : at + batch]], y[order[at : at + batch]]
                responses = self._respond(xb)
                places = [r.argmax(axis=1) for r in responses]
                pooled = np.concatenate([np.take_along_axis(r, p[:, None, :], 1)[:, 0] for r, p in zip(responses, places)], axis=1)
                hidden = np.maximum(pooled + self.bias, 0)
                z = hidden @ self.out + self.out_bias
                z = np.exp(z - z.max(axis=1, keepdims=True))
                z /= z.sum(axis=1, keepdims=True)
                z[np.arange(len(yb)), yb] -= 1
                z /= len(yb)
                back = (z @ self.out.T) * (hidden > 0)
                grads = []
                for i, (w, p) in enumerate(zip(WIDTHS, places)):
                    g = np.zeros_like(self.filters[i])
                    own = back[:, i * FILTERS : (i + 1) * FILTERS]
                    for j in range(w):
                        np.add.at(g[j], (np.take_along_axis(xb, p + j, 1), np.broadcast_to(k, p.shape)), own)
                    grads.append(g)
                grads += [back.sum(axis=0), hidden.T @ z, z.sum(axis=0)]
                step += 1
                for p, g, m, v in zip(params, grads, mean, square):
                    m += 0.1 * (g - m)
                    v += 0.001 * (g * g - v)
                    p -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)).astype(np.float32)


def text_windows(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All windows of classes of a batch of texts, and the number per text."""
    size = off[1:] - off[:-1]
    count = (size + WINDOW - 1) // WINDOW
    row = np.repeat(np.arange(len(size)), count)
    at = (np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)) * WINDOW + off[row]
    index = at[:, None] + np.arange(WINDOW)
    inside = index < off[row + 1][:, None]
    return np.where(inside, CLASS[data[np.minimum(index, max(len(data) - 1, 0))]] if len(data) else 0, 0).astype(np.int16), count


def held_out(doc_id: str):
    """Documents that never take part in learning; those without an id are not held out."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(3)) == 1, F.lit(False))


def train(docs: DataFrame, per_language: int = PER_LANGUAGE, windows: int = WINDOWS, most_languages: int = MOST_LANGUAGES) -> ByteNet | None:
    """A network learnt from a bounded sample; None where there is no label.

    The sample of a language is its ``per_language`` documents of the smallest
    hash, repeated rows once; ``windows`` windows of each reach the driver.  More
    than ``most_languages`` languages raise an error.  Rows without an id are not
    learnt from.
    """
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    labelled = base.where(F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out("doc_id"))
    labelled = labelled.withColumn("h", F.xxhash64("doc_id", "text"))
    counts = labelled.groupBy("lang").agg(F.approx_count_distinct("h").alias("n")).limit(most_languages + 1).collect()
    if len(counts) > most_languages:
        raise ValueError(f"over {most_languages} languages")
    if not counts:
        return None
    # a bound on the hash lets about eight times the sample of a language through, whatever the corpus
    lowest, span = -(1 << 63), (1 << 64) - 1
    bound = {r["lang"]: min((1 << 63) - 1, lowest + span * 8 * per_language // max(r["n"], 1)) for r in counts}
    below = F.create_map(*[F.lit(x) for k, v in bound.items() for x in (k, v)])[F.col("lang")]

    def cut(batches):
        for batch in slices(batches):
            langs, bodies, keys = [], [], []
            for i in range(batch.num_rows):
                x, _ = text_windows(*text_view(batch.column(2).slice(i, 1)))
                if len(x):
                    pick = np.unique(np.linspace(0, len(x) - 1, min(windows, len(x))).astype(np.int64))
                    langs.append(batch.column(1)[i].as_py())
                    bodies.append(x[pick].tobytes())
                    keys.append(batch.column(0)[i].as_py())
            if langs:
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(langs), pa.array(bodies, pa.binary())], ["h", "lang", "body"])

    drawn = labelled.where(F.col("h") <= below).select("h", "lang", "text").mapInArrow(cut, "h long, lang string, body binary").dropDuplicates(["h", "lang"])
    order = W.partitionBy("lang").orderBy("h")
    rows = drawn.withColumn("k", F.row_number().over(order)).where(F.col("k") <= per_language).collect()
    if not rows:
        return None
    rows.sort(key=lambda r: (r["lang"], r["h"]))
    languages = sorted({r["lang"] for r in rows})
    x = [np.frombuffer(r["body"], np.int16).reshape(-1, WINDOW) for r in rows]
    y = np.repeat([languages.index(r["lang"]) for r in rows], [len(w) for w in x])
    net = ByteNet(languages)
    net.fit(np.concatenate(x), y)
    return net.freeze()


def predict(docs: DataFrame, net: ByteNet | None) -> DataFrame:
    """``docs`` columns ``doc_id``, ``lang_pred`` and ``score`` of each row.

    Null texts and texts without a letter are ``und`` with score 0, as is
    everything where no language could be learnt.
    """
    held = docs.sparkSession.sparkContext.broadcast(net)
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def run(batches):
        for part in slices(batches):
            names, scores = label_texts(part.column(1), held.value)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(names), pa.array(scores, pa.float64())], ["doc_id", "lang_pred", "score"])

    return source.mapInArrow(run, "doc_id long, lang_pred string, score double")


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def label_texts(texts: pa.Array, net: ByteNet | None) -> tuple[list[str], list[float]]:
    """Language and score of each text of an Arrow column."""
    letters = [has_letter(t) for t in texts.to_pylist()]
    if net is None or not any(letters):
        return [UNKNOWN] * len(letters), [0.0] * len(letters)
    data, off = text_view(texts)
    total = np.zeros((len(letters), len(net.languages)))
    weight = np.zeros(len(letters))
    # a bounded number of bytes at a time, also inside one long text
    size = off[1:] - off[:-1]
    step = BLOCK_BYTES
    row = 0
    while row < len(size):
        end = max(row + 1, int(np.searchsorted(off, off[row] + step, side="right")) - 1)
        for at in range(int(off[row]), max(int(off[end]), int(off[row]) + 1), step):
            hi = min(int(off[end]), at + step)
            edges = np.clip(off[row : end + 1], at, hi) - at
            x, count = text_windows(data[at:hi], edges)
            if len(x):
                logs = net.log_probabilities(x)
                owner = np.repeat(np.arange(row, end), count)
                np.add.at(total, owner, logs)
                np.add.at(weight, owner, 1)
        row = end
    mean = total / np.maximum(weight, 1)[:, None]
    p = np.exp(mean - mean.max(axis=1, keepdims=True))
    p /= p.sum(axis=1, keepdims=True)
    best = p.argmax(axis=1)
    return [net.languages[b] if ok else UNKNOWN for b, ok in zip(best, letters)], [float(p[i, b]) if ok else 0.0 for i, (b, ok) in enumerate(zip(best, letters))]


def identify_languages(docs: DataFrame) -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` for each row of ``docs``."""
    return predict(docs, train(docs)).select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame, least: float = 0.5) -> DataFrame:
    """The rows whose language the network names with a score of ``least``.

    Rows without text or letters go, as do those no language fits; all columns
    stay.  Where nothing could be learnt, only texts with letters stay.
    """
    held = docs.sparkSession.sparkContext.broadcast(train(docs))
    at = docs.columns.index("text")

    def run(batches):
        for part in slices(batches):
            if held.value is None:
                good = [has_letter(t) for t in part.column(at).to_pylist()]
            else:
                names, scores = label_texts(part.column(at), held.value)
                good = [n != UNKNOWN and s >= least for n, s in zip(names, scores)]
            yield part.filter(pa.array(good, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
