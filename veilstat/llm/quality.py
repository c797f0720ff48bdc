"""Quality scores by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE`` words. Every passage is encoded (character
and word statistics and a 32-way random projection of its word hashes, then a learned
layer); gated attention, tanh times sigmoid, learns from document labels how much each
passage counts; the weighted passage representation gives the score.

The model is fitted on at most ``SAMPLE`` labelled documents, those with the smallest hash
of their id, so the fit has a fixed size at every scale; scoring covers every whole text.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, small_batches, text_slices, tidy
from .textkernel import words

PASSAGE = 64
#: Labelled documents that the fit uses at most.
SAMPLE = 4_000
THRESHOLD = 0.3
HIDDEN = 24
EPOCHS = 40

# Byte classes, counted in 20-bit fields of three words: (upper, lower, digit), (strong, stops, symbols), (high, feed).
_FIELDS = [np.zeros(256, np.uint64) for _ in range(3)]
for _b in range(256):
    _c = chr(_b)
    if _b >= 128:
        _k = 6
    elif _c.isupper():
        _k = 0
    elif _c.islower():
        _k = 1
    elif _c.isdigit():
        _k = 2
    elif _c in "!?":
        _k = 3
    elif _c in ".,;:'\"-()":
        _k = 4
    elif _c == "\n":
        _k = 7
    elif _c in " \t\r\x0b\x0c":
        continue
    else:
        _k = 5
    _FIELDS[_k // 3][_b] = np.uint64(1) << np.uint64(20 * (_k % 3))
_MASK = np.uint64((1 << 20) - 1)
N_FEATURES = 8 + 7 + 32


def passages(data: np.ndarray, offs: np.ndarray, size: int = PASSAGE) -> tuple[np.ndarray, np.ndarray]:
    """(row, features) of every passage; a row without words has one passage of zeros."""
    rows = len(offs) - 1
    row, s, e, h = words(data, offs)
    counts = np.bincount(row, minlength=rows)
    base = np.cumsum(counts) - counts
    if not len(row):
        return np.arange(rows), np.zeros((rows, N_FEATURES), np.float32)
    place = np.arange(len(row)) - base[row]
    head = np.flatnonzero(place % size == 0)
    n = np.diff(head, append=len(row)).astype(np.float64)
    tail = np.append(head[1:], len(row)) - 1
    # Bytes from the passage's first word to the next passage of the text, or its end.
    begin = s[head]
    chars = np.zeros((len(head), 8))
    bounds = np.empty(2 * len(head), np.int64)
    bounds[0::2] = begin
    bounds[1::2] = e[tail]
    inner = bounds if bounds[-1] < len(data) else bounds[:-1]
    for k, field in enumerate(_FIELDS):
        packed = np.add.reduceat(field[data], inner)[0::2]
        for j in range(3 if k < 2 else 2):
            chars[:, 3 * k + j] = (packed >> np.uint64(20 * j)) & _MASK
    total = np.maximum(chars.sum(axis=1, keepdims=True), 1)
    length = (e - s).astype(np.float64)
    mean = np.add.reduceat(length, head) / n
    spread = np.sqrt(np.maximum(np.add.reduceat(length * length, head) / n - mean * mean, 0))
    again = []
    for lag in (1, 2, 3):
        same = np.zeros(len(h))
        same[lag:] = (h[lag:] == h[:-lag]) & (row[lag:] == row[:-lag])
        again.append(np.add.reduceat(same, head) / n)
    signs = np.unpackbits(h.astype("<u4").view(np.uint8).reshape(-1, 4), axis=1)
    sums = np.add.reduceat(signs, head, axis=0, dtype=np.int32)
    features = np.column_stack([chars / total, mean / 8, spread / 8, *again, np.log1p(n) / 4, total[:, 0] / n / 8, (2 * sums / n[:, None] - 1) * 2])
    r = row[head]
    empty = np.flatnonzero(counts == 0)
    if len(empty):
        r = np.concatenate((r, empty))
        features = np.concatenate((features, np.zeros((len(empty), N_FEATURES))))
        order = np.argsort(r, kind="stable")
        r, features = r[order], features[order]
    return r, features.astype(np.float32)


class Model:
    """Encoder, gated attention and output layer; bags are rows of passages with ascending bag numbers."""

    def __init__(self, inputs: int, hidden: int = HIDDEN, seed: int = 7):
        rng = np.random.default_rng(seed)
        draw = lambda *shape: rng.normal(0, 1 / np.sqrt(shape[0]), shape)
        self.p = {"W": draw(inputs, hidden), "b": np.zeros(hidden), "V": draw(hidden, hidden), "U": draw(hidden, hidden), "w": draw(hidden), "u": draw(hidden), "c": np.zeros(1)}
        self.mean, self.scale = np.zeros(inputs), np.ones(inputs)

    def forward(self, x: np.ndarray, heads: np.ndarray) -> dict:
        p = self.p
        size = np.diff(heads, append=len(x))
        bag = np.repeat(np.arange(len(heads)), size)
        h = np.tanh(x @ p["W"] + p["b"])
        t, g = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-np.clip(h @ p["U"], -30, 30)))
        a = (t * g) @ p["w"]
        a = np.exp(a - np.maximum.reduceat(a, heads)[bag])
        a /= np.add.reduceat(a, heads)[bag]
        z = np.add.reduceat(h * a[:, None], heads, axis=0)
        score = 1 / (1 + np.exp(-np.clip(z @ p["u"] + p["c"], -30, 30)))
        return {"x": x, "h": h, "t": t, "g": g, "a": a, "z": z, "score": score, "bag": bag, "heads": heads}

    def gradients(self, f: dict, y: np.ndarray) -> dict:
        p, n = self.p, len(y)
        d = (f["score"] - y) / n
        dz = d[:, None] * p["u"][None, :]
        dzp = dz[f["bag"]]
        da = (dzp * f["h"]).sum(axis=1)
        mean = np.add.reduceat(da * f["a"], f["heads"])[f["bag"]]
        ds = f["a"] * (da - mean)
        dtg = ds[:, None] * p["w"][None, :]
        dt, dg = dtg * f["g"] * (1 - f["t"] ** 2), dtg * f["t"] * f["g"] * (1 - f["g"])
        dh = dzp * f["a"][:, None] + dt @ p["V"].T + dg @ p["U"].T
        dx = dh * (1 - f["h"] ** 2)
        out = {"u": f["z"].T @ d, "c": np.array([d.sum()]), "w": (f["t"] * f["g"]).T @ ds, "V": f["h"].T @ dt, "U": f["h"].T @ dg, "W": f["x"].T @ dx, "b": dx.sum(axis=0)}
        return {k: v + 1e-4 * p[k] for k, v in out.items()}

    def fit(self, bags: list[np.ndarray], y: np.ndarray, epochs: int = EPOCHS, batch: int = 64, seed: int = 13) -> Model:
        every = np.concatenate(bags)
        self.mean, self.scale = every.mean(axis=0), every.std(axis=0) + 1e-3
        bags = [(b - self.mean) / self.scale for b in bags]
        rng = np.random.default_rng(seed)
        m = {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in self.p.items()}
        step = 0
        for epoch in range(epochs):
            rate = 0.01 * (0.5 + 0.5 * np.cos(np.pi * epoch / epochs)) + 1e-4
            order = rng.permutation(len(bags))
            for i in range(0, len(order), batch):
                some = order[i : i + batch]
                x = np.concatenate([bags[j] for j in some])
                heads = np.cumsum([0, *[len(bags[j]) for j in some[:-1]]])
                step += 1
                for k, g in self.gradients(self.forward(x, heads), y[some]).items():
                    m[k][0] = 0.9 * m[k][0] + 0.1 * g
                    m[k][1] = 0.999 * m[k][1] + 0.001 * g * g
                    self.p[k] = self.p[k] - rate * (m[k][0] / (1 - 0.9**step)) / (np.sqrt(m[k][1] / (1 - 0.999**step)) + 1e-8)
        return self

    def score(self, row: np.ndarray, x: np.ndarray, rows: int) -> np.ndarray:
        """Scores of rows 0..rows-1, each with a passage at least."""
        heads = np.searchsorted(row, np.arange(rows))
        return self.forward((x - self.mean) / self.scale, heads)["score"]


def held_out(doc_id) -> F.Column:
    """Whether crc32 of the id as text leaves remainder 0 by 5; null ids are not held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def fit_model(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """A model of ``labels.quality`` from labelled documents that are not held out.

    Documents that are labelled both ways count as often as they are labelled; null labels
    and ids are passed over. Without labels of both kinds the score is their share, or 0.5.
    """
    small_batches(docs.sparkSession)
    usable = only(labels, "doc_id", "quality").where("doc_id is not null and quality is not null").where(~held_out("doc_id"))
    chosen = usable.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(sample)  # the documented bound
    texts = only(docs, "doc_id", "text").join(F.broadcast(chosen), "doc_id")

    def encode(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                row, x = passages(data, offs)
                heads = np.searchsorted(row, np.arange(part.num_rows + 1))
                raw = [x[a:b].tobytes() for a, b in zip(heads[:-1], heads[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(raw, pa.binary())], ["doc_id", "quality", "x"])
        tidy()

    ids, kind = docs.schema["doc_id"].dataType.simpleString(), labels.schema["quality"].dataType.simpleString()
    got = texts.select("doc_id", "text", "quality").mapInArrow(encode, f"doc_id {ids}, quality {kind}, x binary").collect()
    got.sort(key=lambda r: (zlib.crc32(str(r["doc_id"]).encode()), r["doc_id"], r["quality"], r["x"]))
    bags = [np.frombuffer(r["x"], np.float32).reshape(-1, N_FEATURES).astype(np.float64) for r in got]
    y = np.array([float(r["quality"] > 0) for r in got])
    model = Model(N_FEATURES)
    if len(set(y.tolist())) < 2:
        share = y.mean() if len(y) else 0.5
        model.p = {k: np.zeros_like(v) for k, v in model.p.items()}
        model.p["c"] = np.array([np.log((share + 1e-3) / (1 - share + 1e-3))])
        return model
    return model.fit(bags, y)


def score_documents(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted for every row; null and blank texts are one empty passage.

    Rows are independent: repeated and null ids give a row each. An empty table gives an
    empty result; columns other than doc_id and text are ignored.
    """
    small_batches(docs.sparkSession)
    ids = docs.schema["doc_id"].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for batch in batches:
            for part, data, offs in text_slices(batch):
                row, x = passages(data, offs)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(m.score(row, x, part.num_rows))], ["doc_id", "score"])
        tidy()

    scored = only(docs, "doc_id", "text").mapInArrow(run, f"doc_id {ids}, score double")
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_quality(docs: DataFrame, model: Model, threshold: float = THRESHOLD, text: str = "text") -> DataFrame:
    """The rows and columns of ``docs`` whose score reaches ``threshold``, scored where they stand.

    Null and blank texts are one empty passage; repeated rows stay or go together; an empty
    table stays empty; no other column is read.
    """
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for batch in batches:
            for part, data, offs in text_slices(batch, text):
                row, x = passages(data, offs)
                yield part.filter(pa.array(m.score(row, x, part.num_rows) >= threshold))
        tidy()

    return docs.mapInArrow(run, docs.schema)
