"""Document quality by attention-based multiple-instance learning.

A document is a bag of passages of 64 words; only the document has a label.  Every passage is encoded
(surface features, then one learnt layer), a gated attention unit ``w . (tanh(V h) * sigmoid(U h))`` weighs
the passages by softmax over the bag, and a logistic unit scores the weighted representation.  All of it
is trained together on at most ``BAGS`` labelled documents (lowest id hashes) of together at most ``PASSAGES`` passages, each
with all its passages, and applied to all passages of all documents.

Defined cases: a null or empty text is a bag of one all-zero passage; a very long text has as many passages as
it needs; repeated rows get equal scores; a document labelled both ways counts as the larger label; with
no labelled rows, or one label only, every score is that label's rate (0.5 without rows); other columns
are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import by_bytes, labelled_texts, text_array

PASSAGE_WORDS = 64
BUCKETS = 64
BATCH_BYTES = 6 << 20
#: Labelled documents to learn from, and their passages, at most.
BAGS, PASSAGES = 4000, 200_000
SINGLE = b"#*$%&|<>!?.,;:-_/()\"'@=+{}[]"


def _byte_classes() -> np.ndarray:
    kinds = np.zeros(256, np.int64)  # 0: other ASCII
    kinds[97:123], kinds[65:91], kinds[48:58], kinds[128:] = 1, 2, 3, 4
    for k, b in enumerate(SINGLE):
        kinds[b] = 5 + k
    return kinds


BYTE_CLASS = _byte_classes()
N_CLASSES = 5 + len(SINGLE)
N_FEATURES = N_CLASSES + 5 + BUCKETS


def passages(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Feature rows of all passages, and where each text's passages start (and the last ends)."""
    n = len(texts)
    pieces = pc.ascii_split_whitespace(texts)
    filled = pc.binary_length(pieces.values).to_numpy() > 0
    edges = np.concatenate([[0], np.cumsum(filled)])[pieces.offsets.to_numpy()]
    words = pieces.values.filter(pa.array(filled))
    per_text = np.diff(edges)
    bags = np.maximum(1, -(-per_text // PASSAGE_WORDS))
    ends = np.concatenate([[0], np.cumsum(bags)])
    total = int(ends[-1])
    out = np.zeros((total, N_FEATURES), np.float32)
    if not len(words):
        return out, ends
    place = np.arange(len(words)) - np.repeat(edges[:-1], per_text)
    passage = np.repeat(ends[:-1], per_text) + place // PASSAGE_WORDS
    size = pc.binary_length(words).to_numpy().astype(np.int64)
    if words.offset or words.buffers()[2] is None:
        words = pa.concat_arrays([words])
    offsets = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1]
    body = np.frombuffer(words.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
    kinds = np.bincount(np.repeat(passage * N_CLASSES, size) + BYTE_CLASS[body], minlength=total * N_CLASSES).reshape(total, N_CLASSES)
    coded = words.dictionary_encode()
    word = coded.indices.to_numpy().astype(np.int64)
    bucket = np.array([zlib.crc32(w) % BUCKETS for w in pc.ascii_lower(coded.dictionary).cast(pa.binary()).to_pylist()], np.int64)
    n_words = np.bincount(passage, minlength=total).astype(np.float32)
    chars = np.bincount(passage, size, total)
    again = np.concatenate([[False], (word[1:] == word[:-1]) & (passage[1:] == passage[:-1])])
    pairs = np.unique(passage * len(coded.dictionary) + word)
    distinct = np.bincount(pairs // len(coded.dictionary), minlength=total)
    some = np.maximum(n_words, 1)
    out[:, :N_CLASSES] = np.sqrt(kinds / np.maximum(chars, 1)[:, None])
    out[:, N_CLASSES] = distinct / some
    out[:, N_CLASSES + 1] = np.bincount(passage, again, total) / some
    out[:, N_CLASSES + 2] = chars / some / 10
    out[:, N_CLASSES + 3] = np.log1p(n_words) / 4
    out[:, N_CLASSES + 4] = np.repeat(np.log1p(per_text) / 8, bags)
    counts = np.bincount(passage * BUCKETS + bucket[word], minlength=total * BUCKETS).reshape(total, BUCKETS)
    out[:, N_CLASSES + 5 :] = np.sqrt(counts / some[:, None])
    return out, ends


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


@dataclass
class AttentionModel:
    mean: np.ndarray
    scale: np.ndarray
    p: dict[str, np.ndarray]
    constant: float | None = None

    def forward(self, x: np.ndarray, ends: np.ndarray) -> dict[str, np.ndarray]:
        p, bag = self.p, np.repeat(np.arange(len(ends) - 1), np.diff(ends))
        x = (x - self.mean) / self.scale
        h = np.maximum(x @ p["W"] + p["b"], 0)
        t, g = np.tanh(h @ p["V"]), _sigmoid(h @ p["U"])
        e = (t * g) @ p["w"]
        e = np.exp(e - np.maximum.reduceat(e, ends[:-1])[bag])
        a = e / np.add.reduceat(e, ends[:-1])[bag]
        z = np.add.reduceat(a[:, None] * h, ends[:-1], axis=0)
        return {"x": x, "h": h, "t": t, "g": g, "a": a, "z": z, "bag": bag, "score": _sigmoid(z @ p["c"] + p["d"][0])}

    def gradients(self, f: dict[str, np.ndarray], ends: np.ndarray, y: np.ndarray, decay: float) -> dict[str, np.ndarray]:
        p, bag = self.p, f["bag"]
        dy = (f["score"] - y) / len(y)
        dz = dy[:, None] * p["c"]
        da = (dz[bag] * f["h"]).sum(axis=1)
        de = f["a"] * (da - np.add.reduceat(f["a"] * da, ends[:-1])[bag])
        dt, dg = de[:, None] * p["w"] * f["g"] * (1 - f["t"] ** 2), de[:, None] * p["w"] * f["t"] * f["g"] * (1 - f["g"])
        dh = (f["a"][:, None] * dz[bag] + dt @ p["V"].T + dg @ p["U"].T) * (f["h"] > 0)
        found = {"c": f["z"].T @ dy, "d": dy.sum(keepdims=True), "w": (f["t"] * f["g"]).T @ de, "V": f["h"].T @ dt, "U": f["h"].T @ dg, "W": f["x"].T @ dh, "b": dh.sum(axis=0)}
        return {k: v + decay * p[k] * (k not in "db") for k, v in found.items()}

    def scores(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Score of each text, its most attended passage and that one's attention."""
        if self.constant is not None:
            return np.full(len(texts), self.constant), np.zeros(len(texts), np.int64), np.ones(len(texts))
        x, ends = passages(texts)
        f = self.forward(x, ends)
        most = np.maximum.reduceat(f["a"], ends[:-1])
        hit = np.flatnonzero(f["a"] >= most[f["bag"]])
        first = hit[np.searchsorted(hit, ends[:-1])]
        return f["score"], first - ends[:-1], most


def train(x: np.ndarray, ends: np.ndarray, y: np.ndarray, hidden: int = 24, gate: int = 12, epochs: int = 40, batch: int = 128, rate: float = 3e-3, decay: float = 1e-4, seed: int = 7) -> AttentionModel:
    """Adam on the logistic loss of whole bags; reproducible for equal input order."""
    rng = np.random.default_rng(seed)
    mean, scale = x.mean(axis=0), x.std(axis=0) + 0.05
    d = x.shape[1]
    p = {"W": rng.normal(0, d**-0.5, (d, hidden)), "b": np.zeros(hidden), "V": rng.normal(0, hidden**-0.5, (hidden, gate)), "U": rng.normal(0, hidden**-0.5, (hidden, gate)), "w": rng.normal(0, gate**-0.5, gate), "c": rng.normal(0, hidden**-0.5, hidden), "d": np.array([np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))])}
    model = AttentionModel(mean, scale, p)
    first, second = ({k: np.zeros_like(v) for k, v in p.items()} for _ in range(2))
    step = 0
    for epoch in range(epochs):
        order = rng.permutation(len(y))
        for at in range(0, len(y), batch):
            own = order[at : at + batch]
            sizes = ends[own + 1] - ends[own]
            rows = np.concatenate([np.arange(ends[i], ends[i + 1]) for i in own])
            cut = np.concatenate([[0], np.cumsum(sizes)])
            f = model.forward(x[rows], cut)
            step += 1
            speed = rate * (1 - epoch / epochs)
            for k, v in model.gradients(f, cut, y[own], decay).items():
                first[k] = 0.9 * first[k] + 0.1 * v
                second[k] = 0.999 * second[k] + 0.001 * v**2
                p[k] -= speed * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    return model


def fit(texts: DataFrame, most_passages: int = PASSAGES, **options) -> AttentionModel:
    """Learn from rows (h, t, y) of distinct texts, whole ones in the order of their hashes until ``most_passages`` are reached."""
    length = F.ceil(F.size(F.split("t", r"[ \t\n\x0b\f\r]+")) / PASSAGE_WORDS)
    # The rows are bounded by ``BAGS``, so one window may see them all.
    taken = texts.select("h", length.alias("n")).withColumn("upto", F.sum("n").over(Window.orderBy("h"))).filter(F.col("upto") <= most_passages)
    sample = texts.join(F.broadcast(taken.select("h")), "h", "left_semi")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            x, ends = passages(text_array(table.column("t")))
            rows = [x[a:b].astype("<f4").tobytes() for a, b in zip(ends[:-1], ends[1:], strict=True)]
            yield pa.RecordBatch.from_pydict({"h": table.column("h").combine_chunks(), "y": table.column("y").combine_chunks(), "x": pa.array(rows, pa.binary())})

    found = sample.mapInArrow(encode, "h long, y int, x binary").toArrow().sort_by("h")
    y = found.column("y").to_numpy().astype(np.float64)
    if not len(y) or y.min() == y.max():
        return AttentionModel(np.zeros(1), np.ones(1), {}, float(y.mean()) if len(y) else 0.5)
    rows = [np.frombuffer(b, "<f4").reshape(-1, N_FEATURES) for b in found.column("x").to_pylist()]
    return train(np.concatenate(rows), np.concatenate([[0], np.cumsum([len(r) for r in rows])]), y, **options)


def scored(docs: DataFrame, model: AttentionModel, threshold: float = 0.3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key, score, predicted, passage, attention``: the most attended passage and its weight are evidence."""
    kind = docs.schema[key].dataType.simpleString()
    held = docs.sparkSession.sparkContext.broadcast(model)  # a few thousand numbers

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            s, passage, weight = held.value.scores(text_array(table.column("t")))
            yield pa.RecordBatch.from_arrays([table.column("k").combine_chunks(), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32)), pa.array(passage, pa.int32()), pa.array(weight, pa.float64())], [key, "score", "predicted", "passage", "attention"])

    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(score, f"`{key}` {kind}, score double, predicted int, passage int, attention double")


def quality(docs: DataFrame, marks: DataFrame, train: Column | None = None, bags: int = BAGS, **options) -> DataFrame:
    """Scores of every row of ``docs``, learnt from at most ``bags`` labelled documents that meet ``train``."""
    return scored(docs, fit(labelled_texts(docs, marks, "quality", bags, train), **options))
