"""Quality scores by attention-based multiple-instance learning.

A document is a bag of passages. Each passage is encoded from its characters and words; gated attention, learned
from document labels only, weighs the passages; the weighted representation is scored. The model is small and
trained on the driver from the passage features of a bounded labelled sample; features of whole texts, for training as
for scoring, are made in Arrow batches.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import held_out, label_share, labelled_sample
from .textkit import as_bytes, byte_chunks, hash_words, split_words

PASSAGE_BYTES = 384
#: Bound of the labelled sample: rows of each label.
SAMPLE_ROWS = 2_000
HIDDEN, GATE, EPOCHS = 24, 12, 80
CUTOFF = 0.3
_BINS = np.full(256, 97, np.int64)  # other control characters
_BINS[32:128] = np.arange(96)
_BINS[10], _BINS[128:] = 96, 98
N_BINS = 99
N_FEATURES = N_BINS + 5


def passages(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages of all texts, and the first passage of each text (one more entry). An empty text has one empty passage."""
    sizes = np.array([len(t) for t in texts], np.int64)
    cuts = np.maximum(1, -(-sizes // PASSAGE_BYTES))
    first = np.concatenate(([0], np.cumsum(cuts)))
    n = int(first[-1])
    words = split_words(texts)
    flat = np.frombuffer(b"".join(texts), np.uint8)
    text = np.repeat(np.arange(len(texts)), sizes)
    inside = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    passage = first[:-1][text] + inside // PASSAGE_BYTES
    counts = np.bincount(passage * N_BINS + _BINS[flat], minlength=n * N_BINS).reshape(n, N_BINS)
    held = counts.sum(axis=1)
    x = np.zeros((n, N_FEATURES), np.float32)
    x[:, :N_BINS] = np.sqrt(counts / np.maximum(held, 1)[:, None])
    begins = np.concatenate(([0], np.cumsum(sizes + 1)))[:-1]
    doc = np.repeat(np.arange(len(texts)), words.counts)
    spot = first[:-1][doc] + (words.starts - begins[doc]) // PASSAGE_BYTES
    n_words = np.bincount(spot, minlength=n)
    h = hash_words(words)
    key = np.sort((spot.astype(np.uint64) << np.uint64(40)) | (h >> np.uint64(24)))
    fresh = np.append(True, key[1:] != key[:-1])[: len(key)]
    distinct = np.bincount((key[fresh] >> np.uint64(40)).astype(np.int64), minlength=n)
    letters = np.bincount(spot, weights=words.ends - words.starts, minlength=n)
    x[:, N_BINS] = 1 - distinct / np.maximum(n_words, 1)
    x[:, N_BINS + 1] = letters / np.maximum(n_words, 1) / 10
    x[:, N_BINS + 2] = n_words / 80
    x[:, N_BINS + 3] = held / PASSAGE_BYTES
    x[:, N_BINS + 4] = np.log1p(np.repeat(cuts, cuts)) / 5
    return x, first


@dataclass
class Model:
    """Encoder, gated attention and scorer; without weights it gives a constant."""

    constant: float = 0.5
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None
    p: dict[str, np.ndarray] | None = None

    def forward(self, x: np.ndarray, first: np.ndarray) -> dict[str, np.ndarray]:
        p, n = self.p, np.diff(first)
        h = np.tanh(x @ p["E"] + p["e"])
        t, g = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-(h @ p["U"])))
        raw = (t * g) @ p["w"]
        top = np.maximum.reduceat(raw, first[:-1])
        a = np.exp(raw - np.repeat(top, n))
        a /= np.repeat(np.add.reduceat(a, first[:-1]), n)
        z = np.add.reduceat(a[:, None] * h, first[:-1], axis=0)
        return {"x": x, "h": h, "t": t, "g": g, "a": a, "z": z, "y": z @ p["c"] + p["b"]}

    def scores(self, texts: list[bytes]) -> np.ndarray:
        if self.p is None:
            return np.full(len(texts), self.constant)
        x, first = passages(texts)
        y = self.forward((x - self.mean) / self.scale, first)["y"].astype(float)
        return 1 / (1 + np.exp(-np.clip(y, -60, 60)))

    def gradients(self, s: dict[str, np.ndarray], first: np.ndarray, dy: np.ndarray) -> dict[str, np.ndarray]:
        """Gradients of the parameters for the gradient ``dy`` of the documents' logits."""
        p, n = self.p, np.diff(first)
        dz = np.repeat(dy[:, None] * p["c"][None, :], n, axis=0)
        da = (dz * s["h"]).sum(axis=1)
        dh = s["a"][:, None] * dz
        draw = s["a"] * (da - np.repeat(np.add.reduceat(s["a"] * da, first[:-1]), n))
        dt = draw[:, None] * p["w"] * s["g"] * (1 - s["t"] ** 2)
        dg = draw[:, None] * p["w"] * s["t"] * s["g"] * (1 - s["g"])
        dh += dt @ p["V"].T + dg @ p["U"].T
        de = dh * (1 - s["h"] ** 2)
        return {"E": s["x"].T @ de, "e": de.sum(axis=0), "V": s["h"].T @ dt, "U": s["h"].T @ dg, "w": (s["t"] * s["g"]).T @ draw, "c": s["z"].T @ dy, "b": np.array(dy.sum())}


def train(bags: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, seed: int = 6) -> Model:
    """Adam on the logistic loss, a batch of documents at a time; both labels weigh as often as they come."""
    if len(set(labels.tolist())) < 2:
        return Model(constant=float(labels.mean()) if len(labels) else 0.5)
    x = np.concatenate(bags)
    first = np.concatenate(([0], np.cumsum([len(b) for b in bags])))
    mean, scale = x.mean(axis=0), x.std(axis=0) + 0.05
    x = ((x - mean) / scale).astype(np.float32)
    r = np.random.default_rng(seed)
    sizes = {"E": (N_FEATURES, HIDDEN), "e": (HIDDEN,), "V": (HIDDEN, GATE), "U": (HIDDEN, GATE), "w": (GATE,), "c": (HIDDEN,), "b": ()}
    p = {k: r.normal(0, 1 / np.sqrt(s[0]) if s else 0, s) * (k not in ("e", "b")) for k, s in sizes.items()}
    model = Model(mean=mean, scale=scale, p={k: np.asarray(v, np.float32) for k, v in p.items()})
    m, v = {k: np.zeros(s) for k, s in sizes.items()}, {k: np.zeros(s) for k, s in sizes.items()}
    step, batch = 0, 64
    for epoch in range(epochs):
        rate = 0.01 * 0.5 * (1 + np.cos(np.pi * epoch / epochs)) + 1e-4
        order = r.permutation(len(bags))
        for k in range(0, len(order), batch):
            own = order[k : k + batch]
            at = np.concatenate([np.arange(first[i], first[i + 1]) for i in own])
            starts = np.concatenate(([0], np.cumsum(np.diff(first)[own])))
            s = model.forward(x[at], starts)
            dy = (1 / (1 + np.exp(-s["y"])) - labels[own]) / len(own)
            step += 1
            for name, g in model.gradients(s, starts, dy).items():
                g = g + 1e-3 * model.p[name] * (name in "EVU")
                m[name] = 0.9 * m[name] + 0.1 * g
                v[name] = 0.999 * v[name] + 0.001 * g * g
                model.p[name] = (model.p[name] - rate * (m[name] / (1 - 0.9**step)) / (np.sqrt(v[name] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return model


def _bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in byte_chunks(whole, "__text"):
            x, first = passages(as_bytes(b.column(2)))
            bags = [x[i:j].tobytes() for i, j in zip(first[:-1], first[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(bags, pa.binary())], names=["doc_id", "label", "bag"])


def training_bags(documents: DataFrame, labels: DataFrame) -> tuple[list[np.ndarray], np.ndarray]:
    """Features of all passages of every text of the labelled sample, made by the executors, and the labels; in the order of ids."""
    kind = documents.schema["doc_id"].dataType.simpleString()
    sample = labelled_sample(documents, labels, "quality", SAMPLE_ROWS).select("doc_id", "__label", "__text")
    rows = sorted(sample.mapInArrow(_bags, f"doc_id {kind}, label int, bag binary").collect(), key=lambda r: r["doc_id"])
    return [np.frombuffer(r["bag"], np.float32).reshape(-1, N_FEATURES) for r in rows], np.array([r["label"] for r in rows], float)


def fit_quality(documents: DataFrame, labels: DataFrame) -> Model:
    bags, own = training_bags(documents, labels)
    model, share = train(bags, own), label_share(labels, "quality")
    if model.p is not None and share and 0 < share < 1:  # the sample has both labels about equally often
        drawn = own.mean()
        model.p["b"] = model.p["b"] + np.float32(np.log(share / (1 - share)) - np.log(drawn / (1 - drawn)))
    return model


def _scan(model, text: str):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in byte_chunks(whole, text):
                score = pa.array(model.scores(as_bytes(b.column(b.schema.get_field_index(text)))), pa.float64())
                yield pa.RecordBatch.from_arrays([score if f.name == "__score" else b.column(i) for i, f in enumerate(b.schema)], names=b.schema.names)

    return scan


def with_score(documents: DataFrame, model) -> DataFrame:
    """All columns plus ``__score`` from the whole text (null text: empty); works for any model with ``scores``."""
    out = documents.withColumn("__score", F.lit(None).cast("double"))
    return out.mapInArrow(_scan(model, "text"), out.schema)


def score_digest(documents: DataFrame, model, cutoff: float) -> DataFrame:
    """doc_id, held_out, score, predicted for every row; null ids are held out, repeated rows get rows like others."""
    scored = with_score(documents.select("doc_id", "text"), model)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("__score").alias("score"), (F.col("__score") >= cutoff).cast("int").alias("predicted"))


def score_quality(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Quality of every document. Without labels of both kinds the score is the share of label 1, or 0.5."""
    return score_digest(documents, fit_quality(documents, labels), CUTOFF)


def accepted(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents whose score reaches the cutoff, with all their columns."""
    return with_score(documents, fit_quality(documents, labels)).filter(F.col("__score") >= CUTOFF).select(*documents.columns)
