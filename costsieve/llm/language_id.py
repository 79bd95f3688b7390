"""Language identification by a convolutional network over bytes.

Each byte has a small vector; filters of several widths slide over a fixed-length window, the largest response of each filter is kept, and a softmax layer
gives the languages' probabilities. Training is plain numpy on a bounded sample of labelled windows. A text is cut into windows that cover all its bytes;
its probabilities are the mean over windows, weighted by the bytes they hold.

For prediction the byte vectors and filters are multiplied out into tables over byte pairs, so that a filter's response is a sum of one or two rows.

Defined results: a null text, or one without a letter, is ``und`` with the score 0, as is every text if there are no labels to learn from; equal
texts get equal results; a null doc_id is not held out, is never learnt from, and is carried through, as are repeated rows; other columns are ignored (``predict``) or
passed through (``identified``).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import columns
from .memo import only
from .piece_bpe import slices
from .staging import ship

WINDOW = 512
UNDETERMINED = "und"


@dataclass(frozen=True)
class TrainOptions:
    per_language: int = 600  # about so many windows of each language are learnt from
    windows: int = 60_000  # at most about so many in all: with more than a hundred languages each gives fewer, and none is left out
    widths: tuple[int, ...] = (2, 3, 4)
    filters: int = 16
    vector: int = 8
    epochs: int = 14
    rate: float = 0.01
    seed: int = 7


@dataclass
class ByteNet:
    languages: list[str]
    vectors: np.ndarray  # 256 x vector
    kernels: list[np.ndarray]  # width x vector x filters
    biases: list[np.ndarray]
    dense: np.ndarray  # widths*filters x languages
    offset: np.ndarray
    _tables: list[tuple[np.ndarray, ...]] = field(default_factory=list, repr=False)

    def __getstate__(self):
        return self.__dict__ | {"_tables": []}

    def tables(self) -> list[tuple[np.ndarray, ...]]:
        """Per width, rows to add up: over pairs of neighbouring bytes, then one for an odd last byte."""
        if not self._tables:
            for kernel in self.kernels:
                single = [(self.vectors @ kernel[j]).astype(np.float32) for j in range(len(kernel))]
                rows = []
                for j in range(0, len(single) - 1, 2):
                    rows.append((single[j][:, None, :] + single[j + 1][None, :, :]).reshape(65536, -1))
                if len(single) % 2:
                    rows.append(single[-1])
                self._tables.append(tuple(rows))
        return self._tables

    def pooled(self, windows: np.ndarray) -> np.ndarray:
        """n x WINDOW bytes to n x features. Windows are padded with zero bytes, here and in training."""
        n, size = windows.shape
        wide = np.zeros((n, size + max(len(k) for k in self.kernels)), np.uint8)
        wide[:, :size] = windows
        pairs = wide[:, :-1].astype(np.int32) * 256 + wide[:, 1:]
        out = []
        for rows, kernel, bias in zip(self.tables(), self.kernels, self.biases):
            total = None
            for j in range(0, len(kernel), 2):
                source = pairs if j + 1 < len(kernel) else wide
                part = rows[j // 2].take(source[:, j : j + size], axis=0)
                total = part if total is None else np.add(total, part, out=total)
            out.append(np.maximum(total.max(axis=1) + bias, 0))
        return np.concatenate(out, axis=1)

    def probabilities(self, windows: np.ndarray) -> np.ndarray:
        return _softmax(self.pooled(windows) @ self.dense + self.offset)


def _softmax(scores: np.ndarray) -> np.ndarray:
    e = np.exp(scores - scores.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def fit(windows: list[bytes], labels: list[str], options: TrainOptions = TrainOptions()) -> ByteNet:
    """Adam on cross entropy; the gradient of a maximum flows to the place that gave it. Lengths are varied, so that short texts are learnt too."""
    rng = np.random.default_rng(options.seed)
    names = sorted(set(labels))
    target = np.array([names.index(x) for x in labels])
    size = WINDOW
    data = np.zeros((len(windows), size), np.uint8)
    for i, w in enumerate(windows):
        data[i, : len(w[:size])] = np.frombuffer(w[:size], np.uint8)
    lengths = np.array([max(1, min(len(w), size)) for w in windows])
    params = [rng.normal(0, 0.5, (256, options.vector))]
    params[0][0] = 0
    for width in options.widths:
        params += [rng.normal(0, (width * options.vector) ** -0.5, (width, options.vector, options.filters)), np.zeros(options.filters)]
    features = len(options.widths) * options.filters
    params += [rng.normal(0, features**-0.5, (features, len(names))), np.zeros(len(names))]
    first, second, step = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
    for epoch in range(options.epochs):
        order = rng.permutation(len(data))
        rate = options.rate * (1 - epoch / options.epochs)
        for begin in range(0, len(order), 64):
            rows = order[begin : begin + 64]
            keep = np.maximum(1, (lengths[rows] * np.where(rng.random(len(rows)) < 0.5, 1.0, rng.random(len(rows)) ** 2)).astype(int))
            batch = np.where(np.arange(size)[None, :] < keep[:, None], data[rows], 0)[:, : int(keep.max())]
            grads = _gradients(params, batch, target[rows], options)
            step += 1
            for p, g, m, v in zip(params, grads, first, second):
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                p -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
            params[0][0] = 0
    return ByteNet(names, params[0].astype(np.float32), [p.astype(np.float32) for p in params[1:-2:2]], [p.astype(np.float32) for p in params[2:-2:2]], params[-2].astype(np.float32), params[-1].astype(np.float32))


def _gradients(params: list[np.ndarray], batch: np.ndarray, target: np.ndarray, options: TrainOptions) -> list[np.ndarray]:
    n, size = batch.shape
    most = max(options.widths)
    wide = np.zeros((n, size + most), np.uint8)
    wide[:, :size] = batch
    vectors = params[0][wide]
    pooled, places = [], []
    for k, width in enumerate(options.widths):
        kernel, bias = params[1 + 2 * k], params[2 + 2 * k]
        total = sum(vectors[:, j : j + size] @ kernel[j] for j in range(width))
        at = total.argmax(axis=1)
        pooled.append(np.take_along_axis(total, at[:, None, :], axis=1)[:, 0, :] + bias)
        places.append(at)
    raw = np.concatenate(pooled, axis=1)
    active = np.maximum(raw, 0)
    error = _softmax(active @ params[-2] + params[-1])
    error[np.arange(n), target] -= 1
    error /= n
    back = (error @ params[-2].T) * (raw > 0)
    grads = [np.zeros_like(p) for p in params]
    grads[-2], grads[-1] = active.T @ error, error.sum(axis=0)
    row = np.arange(n)[:, None]
    for k, width in enumerate(options.widths):
        part = back[:, k * options.filters : (k + 1) * options.filters]
        grads[2 + 2 * k] = part.sum(axis=0)
        for j in range(width):
            seen = wide[row, places[k] + j]  # n x filters bytes
            grads[1 + 2 * k][j] = np.einsum("nfv,nf->vf", params[0][seen], part)
            np.add.at(grads[0], seen, part[:, :, None] * params[1 + 2 * k][j].T[None, :, :])
    return grads


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def learn(docs: DataFrame, options: TrainOptions = TrainOptions()) -> ByteNet | None:
    """Fit on about ``per_language`` windows of each language, chosen by a hash of doc_id; what is collected is bounded by the options."""
    rows = columns.pick(docs, doc_id="doc_id", text="text", lang="lang")
    known = rows.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    counts = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row per class of the net
    if not counts:
        return None
    each = min(options.per_language, max(1, options.windows // len(counts)))
    draw = F.pmod(F.xxhash64("doc_id", F.lit(options.seed)), F.lit(1 << 30))
    share = F.create_map(*[x for lang, n in sorted(counts.items()) for x in (F.lit(lang), F.lit(int(min(1.0, each / n) * (1 << 30))))])
    data = F.encode("text", "UTF-8")
    begin = F.pmod(F.xxhash64("doc_id", F.lit(options.seed + 1)), F.greatest(F.octet_length("text") - WINDOW + 1, F.lit(1))).cast("int")
    sample = known.where(draw < F.element_at(share, F.col("lang"))).select("lang", "doc_id", data.substr(begin + 1, F.lit(WINDOW)).alias("window")).orderBy("doc_id", "lang", "window").collect()
    return fit([bytes(r["window"]) for r in sample], [r["lang"] for r in sample], options) if sample else None


def predict(docs: DataFrame, model: ByteNet | None) -> DataFrame:
    """(doc_id bigint, lang_pred string, score double) of every whole text."""
    return identified(columns.documents(docs), model, carried=["doc_id"]).toDF("doc_id", "lang_pred", "score")


def identified(docs: DataFrame, model: ByteNet | None, carried: list[str] | None = None) -> DataFrame:
    """The rows of ``docs`` with all their columns, or those ``carried``, under positional names, and (__lang, __score)."""
    ship(docs.sparkSession)
    plain, own_text = columns.positional(docs), f"__c{columns.place(docs, 'text')}"
    names = [f"__c{docs.columns.index(c)}" for c in carried or docs.columns]

    def run(batches):
        only()
        for batch in slices(batches, own_text, 256 << 10):
            texts = batch.column(own_text).to_pylist()
            chosen, scores = [UNDETERMINED] * len(texts), [0.0] * len(texts)
            own = [i for i, t in enumerate(texts) if t and model is not None and any(map(str.isalpha, t))]
            data = [texts[i].encode() for i in own]
            cuts = [-(-len(d) // WINDOW) for d in data]
            flat = np.frombuffer(b"".join(d.ljust(c * WINDOW, b"\0") for d, c in zip(data, cuts)), np.uint8).reshape(-1, WINDOW)
            at = 0
            probs = np.concatenate([model.probabilities(flat[k : k + 64]) for k in range(0, len(flat), 64)]) if len(flat) else None
            for i, d, c in zip(own, data, cuts):
                weights = np.full(c, WINDOW, np.float64)
                weights[-1] = len(d) - (c - 1) * WINDOW
                mean = weights @ probs[at : at + c] / len(d)
                at += c
                best = int(mean.argmax())
                chosen[i], scores[i] = model.languages[best], float(min(1.0, mean[best]))
            yield pa.RecordBatch.from_arrays([*map(batch.column, names), pa.array(chosen, pa.string()), pa.array(scores, pa.float64())], [*names, "__lang", "__score"])

    return plain.mapInArrow(run, T.StructType([*[plain.schema[n] for n in names], T.StructField("__lang", T.StringType()), T.StructField("__score", T.DoubleType())]))


def identify(docs: DataFrame, options: TrainOptions = TrainOptions()) -> DataFrame:
    """Learn from the labelled rows that are not held out, then predict all rows."""
    return predict(docs, learn(docs, options))
