"""Quality by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE_WORDS`` words; only whole documents have labels.
Every passage is encoded (rates of word shapes, marks and repetition, and its words hashed
with a sign into ``WORD_BINS`` places, then a learned tanh layer), gated attention gives it a weight among its document's passages, and the weighted
mean is scored by a logistic unit. All weights, the attention's too, are learned together
from document labels. One passage of junk can so decide about a long document.

Fitting takes a bounded sample of labelled documents, ``fit_docs`` of them by hash of their
id, and of a document with more than ``fit_passages`` passages as many spread evenly over it;
passages are encoded on the executors. Scoring is one pass over the whole texts without
an exchange; the model is some kilobytes.

Defined results: null text is empty; a text without words is one passage of zeros and gets a
score like any other; null labels are not learned from; without labels every score is 0.5;
repeated rows are scored each; empty tables give empty results. Ids, languages, sources and
labels are no inputs of a score.
"""

from __future__ import annotations

from collections.abc import Iterator
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty
from .language_model import U, word_hashes

PASSAGE_WORDS = 48
#: Marks that are counted one by one, and marks that are counted together.
MARKS, TOGETHER = ".,!|?:@/<-\"'()_=;", "#%$&*~^+\\{}[]"
SHAPES, WORD_BINS = len(MARKS) + 14, 64
N_FEATURES = SHAPES + WORD_BINS


def passage_features(ws: list[str]) -> list[float]:
    n, s = len(ws), " ".join(ws)
    size, lengths = len(s), list(map(len, ws))
    distinct = len(set(ws))
    out = [s.count(m) / n for m in MARKS]
    out += [
        sum(map(s.count, TOGETHER)) / n,
        sum(map(str.isupper, ws)) / n,
        sum(map(str.istitle, ws)) / n,
        sum(map(str.isalpha, ws)) / n,
        sum(map(str.isdecimal, ws)) / n,
        sum(map(str.islower, ws)) / n,
        distinct / n,
        sum(map(eq, ws, ws[1:])) / n,
        sum(map(eq, ws, ws[2:])) / n,
        size / n / 10,
        lengths.count(1) / n,
        max(lengths) / 20 if max(lengths) < 200 else 10.0,
        len(set(s)) / size,
        n / PASSAGE_WORDS,
    ]
    return out


def encode(text: str) -> np.ndarray:
    """(passages, N_FEATURES); the last passage takes in a short rest. Words are told apart in
    lower case."""
    words = text.split()
    if not words:
        return np.zeros((1, N_FEATURES), np.float32)
    starts = list(range(0, len(words), PASSAGE_WORDS))
    if len(starts) > 1 and len(words) - starts[-1] < PASSAGE_WORDS // 3:
        starts.pop()
    ends = [*starts[1:], len(words)]
    shapes = np.array([passage_features(words[a:b]) for a, b in zip(starts, ends, strict=True)], dtype=np.float32)
    h = word_hashes(" ".join(words).lower().encode("utf-8", "replace"))
    if len(h) != len(words):  # lower case may bring white space of its own
        h = np.resize(h, len(words))
    sizes = np.subtract(ends, starts)
    place = np.repeat(np.arange(len(starts)), sizes) * WORD_BINS + ((h >> U(50)) % U(WORD_BINS)).astype(np.int64)
    sign = np.where(h & U(1), 1.0, -1.0)
    bins = np.bincount(place, sign, len(starts) * WORD_BINS).reshape(-1, WORD_BINS) / np.sqrt(sizes)[:, None]
    return np.concatenate([shapes, bins.astype(np.float32)], axis=1)


def spread(bag: np.ndarray, most: int) -> np.ndarray:
    """At most so many passages, evenly from the whole document."""
    return bag if len(bag) <= most else bag[np.linspace(0, len(bag) - 1, most).astype(int)]


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class AttentionModel:
    """Encoder, gated attention and logistic score over bags of passages."""

    def __init__(self, hidden: int = 24, gate: int = 12, seed: int = 5):
        r = np.random.default_rng(seed)
        init = lambda *shape: r.standard_normal(shape) / np.sqrt(shape[0])
        self.p = {
            "W": init(N_FEATURES, hidden), "b": np.zeros(hidden), "V": init(hidden, gate), "U": init(hidden, gate),
            "w": init(gate), "c": init(hidden), "d": np.zeros(1),
        }
        self.mean, self.scale = np.zeros(N_FEATURES), np.ones(N_FEATURES)

    def _forward(self, x: np.ndarray, starts: np.ndarray) -> dict[str, np.ndarray]:
        p = self.p
        bag = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(x))))
        h = np.tanh(x @ p["W"] + p["b"])
        t, s = np.tanh(h @ p["V"]), _sigmoid(h @ p["U"])
        e = (t * s) @ p["w"]
        e = np.exp(e - np.maximum.reduceat(e, starts)[bag])
        a = e / np.add.reduceat(e, starts)[bag]
        z = np.add.reduceat(a[:, None] * h, starts)
        return {"bag": bag, "h": h, "t": t, "s": s, "a": a, "z": z, "y": _sigmoid(z @ p["c"] + p["d"])}

    def _scaled(self, bags: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        starts = np.cumsum([0, *map(len, bags[:-1])])
        return np.clip((np.concatenate(bags) - self.mean) / self.scale, -8, 8), starts

    def scores(self, bags: list[np.ndarray]) -> np.ndarray:
        return self._forward(*self._scaled(bags))["y"]

    def attention(self, bag: np.ndarray) -> np.ndarray:
        """A document's attention weights, one a passage."""
        return self._forward(*self._scaled([bag]))["a"]

    def gradients(self, x: np.ndarray, starts: np.ndarray, labels: np.ndarray) -> dict[str, np.ndarray]:
        """Of the mean logistic loss of the documents, by all weights."""
        p, f = self.p, self._forward(x, starts)
        bag, h, t, s, a = f["bag"], f["h"], f["t"], f["s"], f["a"]
        dy = (f["y"] - labels) / len(labels)
        dz = dy[:, None] * p["c"]
        da = np.einsum("ij,ij->i", h, dz[bag])
        de = a * (da - np.add.reduceat(a * da, starts)[bag])
        dg = de[:, None] * p["w"]
        dt, ds = dg * s * (1 - t * t), dg * t * s * (1 - s)
        dh = (a[:, None] * dz[bag] + dt @ p["V"].T + ds @ p["U"].T) * (1 - h * h)
        return {"W": x.T @ dh, "b": dh.sum(axis=0), "V": h.T @ dt, "U": h.T @ ds, "w": (t * s).T @ de, "c": f["z"].T @ dy, "d": dy.sum(keepdims=True)}

    def fit(self, bags: list[np.ndarray], labels: np.ndarray, epochs: int = 30, least_steps: int = 1500, rate: float = 4e-3, decay: float = 1e-3, seed: int = 3) -> AttentionModel:
        """At least ``epochs`` rounds and ``least_steps`` steps; it starts from the labels' base rate."""
        every = np.concatenate(bags)
        batch = min(64, max(8, len(bags) // 16))
        epochs = max(epochs, -(-least_steps * batch // len(bags)))
        base = float(np.clip(np.mean(labels), 0.02, 0.98))
        self.p["d"][:] = np.log(base / (1 - base))
        self.mean, self.scale = every.mean(axis=0), every.std(axis=0) + 1e-3
        p, r, step = self.p, np.random.default_rng(seed), 0
        m, v = {k: np.zeros_like(x) for k, x in p.items()}, {k: np.zeros_like(x) for k, x in p.items()}
        for epoch in range(epochs):
            order = r.permutation(len(bags))
            for i in range(0, len(order), batch):
                pick = order[i : i + batch]
                g = self.gradients(*self._scaled([bags[j] for j in pick]), labels[pick])
                step += 1
                lr = rate * (0.5 + 0.5 * np.cos(np.pi * epoch / epochs))
                for k in p:
                    grad = g[k] + decay * p[k]
                    m[k] = 0.9 * m[k] + 0.1 * grad
                    v[k] = 0.999 * v[k] + 0.001 * grad * grad
                    p[k] -= lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        return self


def held_out(doc_id: Column) -> Column:
    """Rows that labels are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, fit_docs: int = 4000, fit_passages: int = 1000, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> AttentionModel | None:
    """A model from at most ``fit_docs`` labelled documents outside the held-out rows, each with
    at most ``fit_passages`` passages, so that what reaches the driver is bounded."""
    known = labels.select(F.col(id_col).alias("doc_id"), F.col(label_col).cast("double").alias("label")).where(F.col("label").isNotNull() & F.col("doc_id").isNotNull())
    known = known.where(~held_out(F.col("doc_id"))).orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(fit_docs)
    texts = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    rows = texts.join(F.broadcast(known), "doc_id").select("doc_id", "label", "text")

    def passages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            bags = [spread(encode(t.as_py()), fit_passages).tobytes() for t in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(bags, pa.binary())], ["doc_id", "label", "bag"])

    got = rows.mapInArrow(passages, "doc_id bigint, label double, bag binary").toArrow().sort_by([("doc_id", "ascending"), ("label", "ascending")])
    if not got.num_rows:
        return None
    bags = [np.frombuffer(b, np.float32).reshape(-1, N_FEATURES) for b in got.column("bag").to_pylist()]
    return AttentionModel().fit(bags, got.column("label").to_numpy())


def score(docs: DataFrame, model: AttentionModel | None, accept: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score, predicted (1 from ``accept`` up), n_passages and the top passage's weight."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in (batch.slice(i, 500) for i in range(0, batch.num_rows, 500)):
                bags = [encode(t.as_py()) for t in b.column(1)]
                sizes = np.array([len(x) for x in bags])
                if model is None:
                    y, top = np.full(len(bags), 0.5), 1 / sizes
                else:
                    x, starts = model._scaled(bags)
                    f = model._forward(x, starts)
                    y, top = f["y"], np.maximum.reduceat(f["a"], starts)
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), pa.array(y.astype(float)), pa.array((y >= accept).astype(np.int32)), pa.array(sizes.astype(np.int32)), pa.array(top.astype(float))],
                    ["doc_id", "score", "predicted", "n_passages", "top_weight"],
                )

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, score double, predicted int, n_passages int, top_weight double")


def keep_good(docs: DataFrame, model: AttentionModel | None, accept: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose text the model accepts, with all their columns; no exchange.

    Without a model (no labels) every row stays.
    """
    if model is None:
        return docs
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in (batch.slice(i, 500) for i in range(0, batch.num_rows, 500)):
                y = model.scores([encode(t.as_py() or "") for t in b.column(at)])
                yield b.filter(pa.array(y >= accept))

    return docs.mapInArrow(run, docs.schema)
