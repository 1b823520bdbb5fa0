"""Language ID: a byte convolutional network with filters of several widths, max pooling and softmax.

It is trained in numpy on a bounded sample of labelled rows and applied to every window of every text, batch by
batch. A text's score is the mean of its windows' log-probabilities, weighted by their bytes.

Defined results: a null text or one without a letter is ``und`` with score 0; with no labelled row every text is
``und``. Repeated rows are scored alike.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LETTER = regex.compile(r"\p{L}")


class ByteNet:
    """Embedding of bytes, filters of widths ``widths`` as one matrix, maximum over the window, rectifier, softmax."""

    def __init__(self, labels: list[str], widths=(2, 3, 4), filters: int = 16, dim: int = 8, window: int = 256, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.labels, self.widths, self.window, self.span = labels, widths, window, max(widths)
        self.emb = rng.normal(0, 0.5, (256, dim)).astype(np.float32)
        self.emb[0] = 0
        f = filters * len(widths)
        self.mask = np.zeros((self.span, dim, f), np.float32)
        for k, w in enumerate(widths):
            self.mask[:w, :, k * filters:(k + 1) * filters] = 1
        self.w = (rng.normal(0, 0.3, self.mask.shape) * self.mask).astype(np.float32)
        self.b = np.zeros(f, np.float32)
        self.v = rng.normal(0, 0.2, (f, len(labels))).astype(np.float32)
        self.c = np.zeros(len(labels), np.float32)

    def _columns(self, x: np.ndarray) -> np.ndarray:
        e = self.emb[x]
        n, length, dim = e.shape
        s = e.strides
        return np.lib.stride_tricks.as_strided(e, (n, length - self.span + 1, self.span * dim), (s[0], s[1], s[2])).reshape(-1, self.span * dim)

    def logits(self, x: np.ndarray) -> np.ndarray:
        n, at = len(x), x.shape[1] - self.span + 1
        h = (self._columns(x) @ self.w.reshape(-1, self.w.shape[2])).reshape(n, at, -1).max(axis=1) + self.b
        return np.maximum(h, 0) @ self.v + self.c

    def log_prob(self, x: np.ndarray) -> np.ndarray:
        z = self.logits(x)
        z = z - z.max(axis=1, keepdims=True)
        return z - np.log(np.exp(z).sum(axis=1, keepdims=True))

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 6, batch: int = 128, rate: float = 0.01, seed: int = 5) -> ByteNet:
        """Gradient steps with running moments; only the winning place of each filter carries its gradient."""
        rng = np.random.default_rng(seed)
        params = ["emb", "w", "b", "v", "c"]
        m1 = {p: np.zeros_like(getattr(self, p)) for p in params}
        m2 = {p: np.zeros_like(getattr(self, p)) for p in params}
        t, dim = 0, self.emb.shape[1]
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(x), batch):
                xb, yb = x[order[at:at + batch]], y[order[at:at + batch]]
                n, places = len(xb), xb.shape[1] - self.span + 1
                cols = self._columns(xb)
                flat = self.w.reshape(-1, self.w.shape[2])
                a = (cols @ flat).reshape(n, places, -1)
                best = a.argmax(axis=1)
                h = np.take_along_axis(a, best[:, None, :], 1)[:, 0] + self.b
                r = np.maximum(h, 0)
                z = r @ self.v + self.c
                p = np.exp(z - z.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                p[np.arange(n), yb] -= 1
                p /= n
                g = {"v": r.T @ p, "c": p.sum(axis=0)}
                dh = (p @ self.v.T) * (h > 0)
                g["b"] = dh.sum(axis=0)
                rows = cols.reshape(n, places, -1)[np.arange(n)[:, None], best]
                g["w"] = np.einsum("nfk,nf->kf", rows, dh).reshape(self.w.shape) * self.mask
                de = np.einsum("nf,kf->nfk", dh, flat).reshape(n, -1, self.span, dim)
                g["emb"] = np.zeros_like(self.emb)
                where = best[:, :, None] + np.arange(self.span)
                np.add.at(g["emb"], xb[np.arange(n)[:, None, None], where].reshape(-1), de.reshape(-1, dim))
                t += 1
                for name in params:
                    m1[name] = 0.9 * m1[name] + 0.1 * g[name]
                    m2[name] = 0.999 * m2[name] + 0.001 * g[name] ** 2
                    step = rate * (m1[name] / (1 - 0.9**t)) / (np.sqrt(m2[name] / (1 - 0.999**t)) + 1e-8)
                    setattr(self, name, (getattr(self, name) - step).astype(np.float32))
        return self


def windows(texts: list[bytes], window: int, span: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All windows of all texts, zero-padded; the text of each, and how many bytes it holds. Neighbours share span - 1 bytes."""
    stride = window - span + 1
    counts = [max(1, -(-max(1, len(t) - span + 1) // stride)) for t in texts]
    out = np.zeros((sum(counts), window), np.uint8)
    size = np.zeros(len(out), np.int64)
    k = 0
    for t, n in zip(texts, counts):
        data = np.frombuffer(t, np.uint8)
        for i in range(n):
            part = data[i * stride:i * stride + window]
            out[k, :len(part)] = part
            size[k] = len(part)
            k += 1
    return out, np.repeat(np.arange(len(texts)), counts), size


def sample(rows: DataFrame, label: str, bound: int, seed: str = "fit") -> DataFrame:
    """About ``bound`` labelled rows, equal shares for each label and one row of each at least, chosen by a hash of the id."""
    draw = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    counts = rows.groupBy(label).agg(F.count("*").alias("_n"), F.min(draw).alias("_first"))
    share = bound / max(1, counts.count())
    rates = counts.select(label, (F.lit(share) / F.col("_n")).alias("_rate"), "_first")
    return rows.join(rates, label).where((draw < F.col("_rate")) | (draw == F.col("_first"))).select(*rows.columns)


def fit(labelled: DataFrame, *, bound: int = 3000, piece: int = 1024, window: int = 256, epochs: int = 6) -> ByteNet | None:
    """Train on at most about ``bound`` rows of (doc_id, text, lang); of each, ``piece`` bytes from a hashed place."""
    chosen = sample(labelled.where("lang is not null and text is not null and text <> ''"), "lang", bound)
    place = F.pmod(F.xxhash64("doc_id"), F.greatest(F.lit(1), F.length("text") - piece)).cast("int") + 1
    rows = chosen.select("doc_id", F.substring("text", place, F.lit(piece)).alias("t"), "lang").collect()
    rows = sorted((r for r in rows if LETTER.search(r.t)), key=lambda r: (str(r.doc_id), r.t))
    labels = sorted({r.lang for r in rows})
    if not labels:
        return None
    net = ByteNet(labels, window=window)
    x, owner, _ = windows([r.t.encode() for r in rows], window, net.span)
    y = np.array([labels.index(r.lang) for r in rows])[owner]
    return net.fit(x, y, epochs)


def predict(docs: DataFrame, net: ByteNet | None, *, text: str = "text", carry: tuple[str, ...] = ("doc_id",), block: int = 256) -> DataFrame:
    """``carry`` columns with lang_pred and score of every row."""
    held = docs.sparkSession.sparkContext.broadcast(net)
    rows = docs.select(*carry, F.col(text).alias("_text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name != "_text")

    def step(batches):
        net = held.value
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("_text")).to_pylist()
            named: list[str] = ["und"] * len(texts)
            score = np.zeros(len(texts))
            todo = [k for k, t in enumerate(texts) if net is not None and t and LETTER.search(t)]
            if todo:
                total = np.zeros((len(todo), len(net.labels)))
                weight = np.zeros(len(todo))
                for first, last in _groups([len(texts[k]) for k in todo], 1 << 19):
                    x, owner, size = windows([texts[k].encode("utf-8", "replace") for k in todo[first:last]], net.window, net.span)
                    for at in range(0, len(x), block):
                        lp = net.log_prob(x[at:at + block]) * size[at:at + block, None]
                        np.add.at(total, owner[at:at + block] + first, lp)
                        np.add.at(weight, owner[at:at + block] + first, size[at:at + block])
                mean = total / np.maximum(weight, 1)[:, None]
                p = np.exp(mean - mean.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                for k, i, s in zip(todo, p.argmax(axis=1), p.max(axis=1)):
                    named[k], score[k] = net.labels[i], s
            keep = [batch.column(i) for i, n in enumerate(batch.schema.names) if n != "_text"]
            yield pa.RecordBatch.from_arrays([*keep, pa.array(named), pa.array(score)], [*[n for n in batch.schema.names if n != "_text"], "lang_pred", "score"])

    return rows.mapInArrow(step, f"{schema}, lang_pred string, score double")


def _groups(sizes: list[int], most: int):
    """Slices of neighbours of at most ``most`` in all; one larger item is a slice of its own."""
    first, held = 0, 0
    for k, n in enumerate(sizes):
        if held and held + n > most:
            yield first, k
            first, held = k, 0
        held += n
    if sizes:
        yield first, len(sizes)
