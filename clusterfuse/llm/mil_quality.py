"""Quality scores by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE`` words, all of them. Each passage is encoded from statistics of its own
words and of what they repeat in the document; gated attention weighs the passages, and the weighted representation is
scored. Only document labels are learned from, of a bounded sample; weights are trained by full-batch gradient descent
on the driver and travel inside the scoring function (a few thousand numbers).

Scores depend on the text alone. Null and empty texts are one empty passage and get its score. Repeated rows get equal
scores; an empty table gives an empty result; without learnable labels of both kinds every score is 0.5. Columns other
than doc_id and text are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import table
from .near_dup import _mix, word_hashes

PASSAGE = 64
#: Labelled rows that are learned from, at most; the first ones by hash of doc_id.
MAX_LABELLED = 3000
CUT = 0.7
HIDDEN, GATE, EPOCHS, RATE, DECAY = 24, 12, 400, 0.02, 1e-4
N_FEATURES = 17
_U = np.uint64
_KIND = np.zeros((5, 256), bool)
_KIND[0, list(b"#*$%&|<>")] = True
_KIND[1, 48:58] = True
_KIND[2, 65:91] = True
_KIND[3, 128:] = True
_KIND[4, list(b".,;:!?'\"()-")] = True


def passages(text: bytes) -> np.ndarray:
    """Features (passages x N_FEATURES) of the whole text; one row of zeros without words."""
    raw = np.frombuffer(text, np.uint8)
    blank = ((raw >= 9) & (raw <= 13)) | (raw == 32)
    edge = np.flatnonzero(np.diff(blank.astype(np.int8), prepend=1, append=1))
    begin, end = edge[0::2], edge[1::2]
    n = len(begin)
    if not n:
        return np.zeros((1, N_FEATURES), np.float32)
    h, length = word_hashes(text), (end - begin).astype(np.float64)
    start = np.arange(0, n, PASSAGE)
    size = np.diff(np.append(start, n)).astype(np.float64)
    mean = lambda x: np.add.reduceat(x.astype(np.float64), start) / size
    avg = mean(length)
    out = [avg, np.sqrt(np.maximum(mean(length**2) - avg**2, 0))]
    first, last = begin[start], end[np.append(start[1:], n) - 1]
    for kind in _KIND:
        total = np.concatenate([[0], np.cumsum(kind[raw])])
        out.append((total[last] - total[first]) / size)
    # distinct words of a passage, and of the document up to here
    part = np.repeat(np.arange(len(start)), size.astype(int))
    order = np.lexsort((h, part))
    new = np.ones(n, bool)
    new[order[1:]] = (h[order][1:] != h[order][:-1]) | (part[order][1:] != part[order][:-1])
    out.append(mean(new))
    seen = np.zeros(n, bool)
    seen[np.unique(h, return_index=True)[1]] = True
    out.append(mean(seen))
    out.append(mean(np.concatenate([h[1:] == h[:-1], [False]])))
    # words in eight-word windows that stand twice in the document
    again = np.zeros(n + 1)
    if n >= 8:
        w = h[: n - 7].copy()
        for k in range(1, 8):
            w = _mix(w) + h[k : n - 7 + k]
        _, back, times = np.unique(w, return_inverse=True, return_counts=True)
        at = np.flatnonzero(times[back] > 1)
        np.add.at(again, at, 1)
        np.add.at(again, at + 8, -1)
    out.append(mean(np.cumsum(again)[:n] > 0))
    # words in lines that repeat an earlier line
    line = np.searchsorted(np.flatnonzero(raw == 10), begin)
    head = np.flatnonzero(np.diff(line, prepend=-1))
    inside = np.arange(n) - np.repeat(head, np.diff(np.append(head, n)))
    key = np.add.reduceat(_mix(h + inside.astype(_U) * _U(0x9E3779B97F4A7C15)), head)
    repeat = np.ones(len(head), bool)
    repeat[np.unique(key, return_index=True)[1]] = False
    out.append(mean(np.repeat(repeat, np.diff(np.append(head, n)))))
    out.append(np.log1p(1 / np.maximum(mean(np.diff(line, prepend=line[0])), 1 / (4 * PASSAGE))))
    out += [size / PASSAGE, np.full(len(start), np.log1p(n)), np.full(len(start), len(np.unique(h)) / n), mean(length > 20)]
    return np.stack(out, axis=1).astype(np.float32)


class Model:
    """Encoder, gated attention and score; ``score`` takes the passages of many documents and where each begins."""

    NAMES = ("w1", "b1", "v", "u", "w", "c", "c0")

    def __init__(self, centre, spread, params: dict):
        self.centre, self.spread, self.p = centre, spread, params

    def _scaled(self, x):
        return np.clip((x - self.centre) / self.spread, -6, 6)

    def forward(self, x, start):
        p = self.p
        size = np.diff(np.append(start, len(x)))
        doc = np.repeat(np.arange(len(start)), size)
        h = np.tanh(x @ p["w1"] + p["b1"])
        t, s = np.tanh(h @ p["v"]), 1 / (1 + np.exp(-(h @ p["u"])))
        e = (t * s) @ p["w"]
        e = np.exp(e - np.maximum.reduceat(e, start)[doc])
        a = e / np.add.reduceat(e, start)[doc]
        z = np.add.reduceat(a[:, None] * h, start)
        out = 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["c0"], -30, 30)))
        return doc, h, t, s, a, z, out

    def score(self, x, start):
        return self.forward(self._scaled(x), start)[-1]

    def attention(self, x, start):
        return self.forward(self._scaled(x), start)[4]


def train(bags: list[np.ndarray], labels: np.ndarray, seed: int = 5) -> Model | None:
    """Fit on bags of passages and 0/1 labels; None unless both labels are there."""
    y = np.asarray(labels, np.float64)
    if not len(y) or y.min() == y.max():
        return None
    rng = np.random.default_rng(seed)
    raw = np.concatenate(bags).astype(np.float64)
    start = np.concatenate([[0], np.cumsum([len(b) for b in bags])[:-1]])
    p = {
        "w1": rng.normal(0, N_FEATURES**-0.5, (N_FEATURES, HIDDEN)),
        "b1": np.zeros(HIDDEN),
        "v": rng.normal(0, HIDDEN**-0.5, (HIDDEN, GATE)),
        "u": rng.normal(0, HIDDEN**-0.5, (HIDDEN, GATE)),
        "w": rng.normal(0, GATE**-0.5, GATE),
        "c": rng.normal(0, HIDDEN**-0.5, HIDDEN),
        "c0": np.zeros(1),
    }
    model = Model(raw.mean(0), raw.std(0) + 1e-6, p)
    x = model._scaled(raw)
    first, second = ({k: np.zeros_like(v) for k, v in p.items()} for _ in range(2))
    for epoch in range(1, EPOCHS + 1):
        doc, h, t, s, a, z, out = model.forward(x, start)
        d = (out - y) / len(y)
        g = {"c": z.T @ d, "c0": np.array([d.sum()])}
        dz = d[:, None] * p["c"]
        dh = a[:, None] * dz[doc]
        da = (h * dz[doc]).sum(1)
        de = a * (da - np.add.reduceat(a * da, start)[doc])
        g["w"] = (t * s).T @ de
        dg = de[:, None] * p["w"]
        dt, ds = dg * s * (1 - t * t), dg * t * s * (1 - s)
        g["v"], g["u"] = h.T @ dt, h.T @ ds
        dh += dt @ p["v"].T + ds @ p["u"].T
        dh *= 1 - h * h
        g["w1"], g["b1"] = x.T @ dh, dh.sum(0)
        for k in p:
            grad = g[k] + DECAY * p[k]
            first[k] = 0.9 * first[k] + 0.1 * grad
            second[k] = 0.999 * second[k] + 0.001 * grad**2
            p[k] -= RATE * (first[k] / (1 - 0.9**epoch)) / (np.sqrt(second[k] / (1 - 0.999**epoch)) + 1e-8)
    return model


def held_out(doc_id) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 4 == 2


def learn_from(docs: DataFrame, labels: DataFrame, limit: int = MAX_LABELLED) -> Model | None:
    """Model from at most ``limit`` labelled rows (doc_id, quality) that are not held out."""
    usable = labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 != 2))
    sample = usable.select("doc_id", "quality").orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(limit)
    known = docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id")  # bounded by ``limit``

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for i, (d, q, t) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).cast(pa.binary()))):
                x = passages(t.as_py() or b"")
                yield pa.RecordBatch.from_arrays([pa.array([d], pa.int64()), pa.array([q], pa.int32()), pa.array([x.tobytes()])], names=["doc_id", "quality", "bag"])

    bags = known.select("doc_id", F.col("quality").cast("int"), "text").mapInArrow(run, "doc_id long, quality int, bag binary")
    # a doc_id that stands on many rows joins its label to all of them: the bound holds for rows too
    found = bags.orderBy(F.xxhash64("doc_id"), "doc_id", "quality", "bag").limit(limit).collect()
    found.sort(key=lambda r: (r["doc_id"], r["quality"], bytes(r["bag"])))
    return train([np.frombuffer(bytes(r["bag"]), np.float32).reshape(-1, N_FEATURES) for r in found], np.array([r["quality"] for r in found]))


def quality_scores(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of ``docs`` (doc_id, text)."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            ids, texts = b.column(0).to_pylist(), b.column(1).cast(pa.binary())
            for at in range(0, len(ids), 256):
                part = ids[at : at + 256]
                bags = [passages(t.as_py() or b"") for t in texts[at : at + 256]]
                start = np.concatenate([[0], np.cumsum([len(x) for x in bags])[:-1]])
                # the last digits depend on which texts share a product of matrices
                score = np.full(len(part), 0.5) if model is None else model.score(np.concatenate(bags).astype(np.float64), start).round(9)
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array([held_out(d) for d in part]), pa.array(score), pa.array((score >= CUT).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def query(spark, sf_dir):
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return quality_scores(docs, learn_from(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))
