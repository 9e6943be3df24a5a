"""Quality classifier by attention-based multiple-instance learning (operator 8).

A document is a bag of passages with one label. Every passage is encoded from its bytes
(transitions between character classes, word repetition, word lengths); a gated attention
weights the passages, and the weighted representation is scored. The weights are learned
from document labels only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.llm.common import slices
from binflow.storage import ship_package

#: bytes of a passage; labelled documents that the model is fitted on (the smallest hashes of the id)
PASSAGE, SAMPLE = 1000, 6000
HIDDEN, GATE, EPOCHS, BAGS, RATE, DECAY = 32, 16, 15, 128, 3e-3, 1e-5
CLASSES = 16
EXTRA = 4
#: steps of 1 that scores are computed on
GRID = 1 << 16
FEATURES = CLASSES * CLASSES + EXTRA


def _byte_classes() -> np.ndarray:
    kind = np.full(256, 15, np.uint8)
    kind[0x80:] = 0
    kind[ord("a") : ord("z") + 1] = 1
    kind[ord("A") : ord("Z") + 1] = 2
    kind[ord("0") : ord("9") + 1] = 3
    for k, chars in enumerate([" \t", "\n\r", ".", ",;:", "!?", "'\"", "()[]{}<>", "/\\-_", "#$%&*@", "|", "=+~^"]):
        for c in chars:
            kind[ord(c)] = 4 + k
    return kind


_KIND = _byte_classes()


def encode_passages(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Feature rows of all passages of the texts, and the number of passages of each text (one at least)."""
    raw = [(t or "").encode() for t in texts]
    size = np.array([len(r) for r in raw], np.int64)
    n = np.maximum(1, (size + PASSAGE // 2) // PASSAGE)
    doc = np.repeat(np.arange(len(raw)), n)
    nth = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
    begin = np.cumsum(size) - size
    start = begin[doc] + nth * size[doc] // n[doc]
    end = begin[doc] + (nth + 1) * size[doc] // n[doc]
    length = end - start
    flat = np.frombuffer(b"".join(raw) + bytes(8), np.uint8)
    total = len(flat) - 8
    passage = np.repeat(np.arange(len(doc), dtype=np.int64), length)
    kind = _KIND[flat[:total]].astype(np.int64)
    final = np.zeros(total, bool)  # the last byte of a text: neither pairs nor words go on into the next one
    final[(begin + size - 1)[size > 0]] = True
    pair = (passage[:-1] * CLASSES * CLASSES + kind[:-1] * CLASSES + kind[1:])[~final[:-1]] if total else np.empty(0, np.int64)
    out = np.zeros((len(doc), FEATURES), np.float32)
    counts = np.bincount(pair, minlength=len(doc) * CLASSES * CLASSES).reshape(len(doc), -1)
    out[:, : CLASSES * CLASSES] = np.sqrt(counts / np.maximum(1, length)[:, None])

    blank = (kind == 4) | (kind == 5)
    first = np.flatnonzero(~blank & np.r_[True, (blank | final)[:-1]]) if total else np.empty(0, np.int64)
    last = np.flatnonzero(~blank & (np.r_[blank[1:], True] | final)) if total else np.empty(0, np.int64)
    width = last - first + 1
    window = np.lib.stride_tricks.sliding_window_view(flat, 8)
    mask = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
    key = np.ascontiguousarray(window[first]).view(np.uint64).reshape(-1) & mask[np.minimum(width, 8)]
    of = passage[first]
    words = np.bincount(of, minlength=len(doc))
    order = np.lexsort((key, of))
    new = np.r_[True, (np.diff(of[order]) != 0) | (key[order][1:] != key[order][:-1])] if len(of) else np.empty(0, bool)
    distinct = np.bincount(of[order][new], minlength=len(doc))
    some = np.maximum(1, words)
    mean = np.bincount(of, width, minlength=len(doc)) / some
    out[:, -4] = distinct / some
    out[:, -3] = np.log1p(mean)
    out[:, -2] = np.log1p(np.sqrt(np.maximum(0, np.bincount(of, width.astype(float) ** 2, minlength=len(doc)) / some - mean**2)))
    out[:, -1] = np.log1p(size[doc]) / 10
    return out, n


@dataclass
class Model:
    """Parameters of the network; a constant prior if the labels were of one kind."""

    prior: float
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None
    weights: dict[str, np.ndarray] | None = None

    def score(self, x: np.ndarray, n: np.ndarray) -> np.ndarray:
        if self.weights is None:
            return np.full(len(n), self.prior)
        return _forward(self.weights, (x - self.mean) / self.scale, n, _exact_product)[0]


def _on_grid(x: np.ndarray) -> np.ndarray:
    return np.rint(x * GRID) / GRID


def _exact_product(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Matrix product without rounding: sums of multiples of 1 / GRID^2 below 2^21 fit a double, so a row's result does not depend on the rows beside it."""
    return _on_grid(np.clip(x, -1024, 1024)) @ w


def _forward(w: dict[str, np.ndarray], x: np.ndarray, n: np.ndarray, product=np.matmul):
    first = np.cumsum(n) - n
    h = np.maximum(0, product(x, w["encode"]) + w["encode0"])
    t, s = np.tanh(product(h, w["content"])), 1 / (1 + np.exp(-np.clip(product(h, w["gate"]), -30, 30)))
    e = product(t * s, w["attend"])
    e = np.exp(e - np.repeat(np.maximum.reduceat(e, first), n))
    a = e / np.repeat(np.add.reduceat(e, first), n)
    z = np.add.reduceat(a[:, None] * h, first, axis=0)
    y = 1 / (1 + np.exp(-np.clip(product(z, w["score"]) + w["score0"], -30, 30)))
    return y, h, t, s, a, z, first


def fit(x: np.ndarray, n: np.ndarray, labels: np.ndarray, seed: int = 42) -> Model:
    """Train on bags of passages. Adam on the log loss, in doubles; the result depends on the inputs' order and the seed only.

    The weights are rounded to the grid on which scores are computed without rounding, which
    also hides the last bits that a BLAS with another number of threads may change.
    """
    prior = (labels.sum() + 1) / (len(labels) + 2)
    if len(np.unique(labels)) < 2:
        return Model(float(prior))
    mean, scale = x.mean(axis=0, dtype=np.float64), x.std(axis=0, dtype=np.float64) + 0.02
    rng = np.random.default_rng(seed)
    w = {"encode": rng.normal(size=(x.shape[1], HIDDEN)) * x.shape[1] ** -0.5, "encode0": np.zeros(HIDDEN), "content": rng.normal(size=(HIDDEN, GATE)) * HIDDEN**-0.5, "gate": rng.normal(size=(HIDDEN, GATE)) * HIDDEN**-0.5, "attend": rng.normal(size=GATE) * GATE**-0.5, "score": rng.normal(size=HIDDEN) * HIDDEN**-0.5, "score0": np.array(np.log(prior / (1 - prior)))}
    m, v = ({k: np.zeros_like(p) for k, p in w.items()} for _ in range(2))
    first, step = np.cumsum(n) - n, 0
    for _ in range(EPOCHS):
        order = rng.permutation(len(n))
        for at in range(0, len(order), BAGS):
            bags = order[at : at + BAGS]
            size = n[bags]
            rows = np.repeat(first[bags] - np.cumsum(size) + size, size) + np.arange(int(size.sum()))
            xb = (x[rows] - mean) / scale
            y, h, t, s, a, z, start = _forward(w, xb, size)
            dy = (y - labels[bags]) / len(bags)
            dz = dy[:, None] * w["score"]
            rep = np.repeat(dz, size, axis=0)
            da = (h * rep).sum(axis=1)
            de = a * (da - np.repeat(np.add.reduceat(a * da, start), size))
            dg = de[:, None] * w["attend"]
            dt, ds = dg * s * (1 - t * t), dg * t * s * (1 - s)
            dh = (a[:, None] * rep + dt @ w["content"].T + ds @ w["gate"].T) * (h > 0)
            grads = {"encode": xb.T @ dh, "encode0": dh.sum(axis=0), "content": h.T @ dt, "gate": h.T @ ds, "attend": (t * s).T @ de, "score": z.T @ dy, "score0": dy.sum()}
            step += 1
            for k, g in grads.items():
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                w[k] = w[k] - RATE * (m[k] / (1 - 0.9**step) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8) + DECAY * w[k])
    return Model(float(prior), mean, scale, {k: _on_grid(np.clip(p, -8, 8)) for k, p in w.items()})


def held_out(id_col: str):
    """The fold that training never sees: crc32 of the id's text modulo 3 is 1; false for a null id."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sample: int = SAMPLE) -> Model:
    """Fit the model on at most ``sample`` labelled documents, those with the smallest hashes of the id among the rows not held out.

    ``sample`` bounds what reaches the driver: the features of their passages. Labels other
    than 0 and 1 and null ids are passed over; of repeated labels the smallest counts, and of
    repeated documents each row. Empty tables, or labels of one kind, give a constant prior.
    Other columns, whatever their names, are not read.
    """
    ship_package(docs.sparkSession)
    known = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull() & ~held_out(id_col))
    known = known.groupBy(F.col(id_col).alias("id")).agg(F.min(label_col).cast("int").alias("y"))
    ids = docs.where(~held_out(id_col)).select(F.col(id_col).alias("id")).distinct()
    chosen = known.join(ids, "id", "left_semi").orderBy(F.xxhash64("id"), "id").limit(sample)
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text"):
                x, n = encode_passages(batch.column("text").to_pylist())
                parts = [p.tobytes() for p in np.split(x, np.cumsum(n)[:-1])]
                yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("y"), pa.array(parts, pa.binary())], ["id", "y", "x"])

    kind = dict(docs.dtypes)[id_col]
    rows = texts.select("id", "text", "y").mapInArrow(run, f"id {kind}, y int, x binary").toArrow().sort_by([("id", "ascending"), ("x", "ascending")]).to_pydict()
    if not rows["y"]:
        return Model(0.5)
    bags = [np.frombuffer(b, np.float32).reshape(-1, FEATURES) for b in rows["x"]]
    return fit(np.concatenate(bags), np.array([len(b) for b in bags]), np.array(rows["y"], np.float32))


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: bool = False) -> DataFrame:
    """(id, held_out, score, predicted) of every row, or with ``keep`` the rows predicted 1 as they were.

    Whole texts are scored: a longer one has more passages. Null, empty and blank texts are
    one passage without words, scored like any other. Rows keep their number, repeated and
    null ids included; equal texts have equal scores; an empty table gives no rows; other
    columns are not read (with ``keep`` they are passed on). Without usable labels of both
    kinds every score is the prior. A very long text is encoded on its own, with about 40 bytes
    of memory for each of its bytes.
    """
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def scores(texts: list[str | None]) -> np.ndarray:
        return np.clip(shared.value.score(*encode_passages(texts)), 0.0, 1.0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text"):
                y = scores(batch.column("text").to_pylist())
                if keep:
                    yield pa.RecordBatch.from_struct_array(batch.column("row").filter(pa.array(y >= 0.5)))
                else:
                    yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("held_out"), pa.array(y), pa.array((y >= 0.5).astype(np.int32))], ["id", "held_out", "score", "predicted"])

    if keep:
        return docs.select(F.col(text_col).alias("text"), F.struct("*").alias("row")).mapInArrow(run, docs.schema)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), held_out(id_col).alias("held_out"))
    return rows.mapInArrow(run, f"id {dict(docs.dtypes)[id_col]}, held_out boolean, score double, predicted int").withColumnRenamed("id", id_col)
