"""Toxicity by maximum-scoring segments of token log-odds.

Log-odds with an informative Dirichlet prior are learnt from a bounded sample of labelled rows. A linear-time scan
finds every maximal segment of each text; their scores are set against the extreme-value law of chance segments,
whose decay solves the moment equation of the background, and the significant ones are added up. A logistic
curve, fitted on the same sample, turns the sum into a score. The word thresholds are chosen by two halves of that
sample, so no row outside it bears on them.

Defined results: a null, empty or wordless text gets the score of no evidence; without labels of both kinds every
score is the share of toxic rows (0 if there is none). Repeated rows are scored alike.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.llm.language import sample
from starfold.llm.shared import text_words

#: Least signed root of the likelihood ratio and least toxic texts of a word, to choose from by rows left out.
GRID = tuple((least_g, texts) for least_g in (3.0, 4.0, 6.0) for texts in (2, 3))


def maximal_segments(scores: list[tuple[int, float]]) -> list[tuple[float, int, int]]:
    """Every maximal scoring segment (score, first, last place) of (place, score) steps, in linear time.

    Each positive step opens a candidate with the sums before and after it; a candidate joins back to the nearest
    one with a smaller sum before, as long as that widens the score.
    """
    held: list[list] = []  # left sum, right sum, first, last, index of the nearest earlier one with a smaller left sum
    total = 0.0
    for place, s in scores:
        if s <= 0:
            total += s
            continue
        new = [total, total + s, place, place, -1]
        total += s
        while True:
            k = len(held) - 1
            while k >= 0 and held[k][0] >= new[0]:
                k = held[k][4]
            if k < 0 or held[k][1] >= new[1]:
                new[4] = k
                held.append(new)
                break
            new = [held[k][0], new[1], held[k][2], new[3], -1]
            del held[k:]
    return [(r - left, a, b) for left, r, a, b, _ in held]


class ToxicModel:
    def __init__(self):
        self.weights: dict[bytes, float] = {}
        self.drift = -0.1
        self.decay, self.scale = 1.0, 0.1
        self.a, self.b = 0.0, -20.0
        self.prior: float | None = 0.0

    def steps(self, words: list[bytes]) -> list[tuple[int, float]]:
        """Tokens with weight, and each stretch between them as one step of the background's drift."""
        get = self.weights.get
        out, last = [], -1
        for k, w in enumerate(words):
            s = get(w)
            if s is not None:
                if k - last > 1:
                    out.append((last + 1, self.drift * (k - last - 1)))
                out.append((k, s))
                last = k
        return out

    def evidence(self, words: list[bytes]) -> tuple[float, list[tuple[float, int, int]]]:
        """Sum of -log E over the segments that chance explains less than once, and those segments."""
        found = []
        total = 0.0
        n = max(1, len(words))
        for s, a, b in maximal_segments(self.steps(words)):
            log_e = math.log(self.scale * n) - self.decay * s
            if log_e < 0:
                found.append((s, a, b))
                total -= log_e
        return total, found

    def score(self, words: list[bytes]) -> float:
        if self.prior is not None:
            return self.prior
        z = self.a * math.log1p(self.evidence(words)[0]) + self.b
        return 1 / (1 + math.exp(-max(-60.0, min(60.0, z))))


def _tally(texts: list[tuple[list[bytes], int]]) -> tuple[list[Counter], list[Counter]]:
    """Words of each label, and the texts of each label that a word is in."""
    counts, spread = [Counter(), Counter()], [Counter(), Counter()]
    for ws, y in texts:
        counts[y].update(ws)
        spread[y].update(set(ws))
    return counts, spread


def train(rows: list[tuple[str, int]], share: float, grid: tuple[tuple[float, int], ...] = GRID, strength: float = 500.0, least_share: float = 0.3) -> ToxicModel:
    """``rows`` are (text, label); ``share`` is the true share of toxic rows, since the sample is balanced.

    Least evidence and least toxic texts of a word are the point of ``grid`` whose scores lose least on halves of
    ``rows`` that were not learnt from; equal texts are in one half.
    """
    texts = [(text_words(t), y) for t, y in rows]
    if len({y for _, y in texts}) < 2:
        model = ToxicModel()
        model.prior = float(share)
        return model
    half = [zlib.crc32(t.encode("utf-8", "surrogatepass")) & 1 for t, _ in rows]
    lost = [0.0] * len(grid)
    for h in (0, 1):
        known = [x for x, k in zip(texts, half) if k != h]
        asked = [x for x, k in zip(texts, half) if k == h]
        if len(grid) < 2 or len({y for _, y in known}) < 2 or not asked:
            continue
        tally = _tally(known)
        y = np.array([y for _, y in asked], float)
        wt = _label_weights(y, share, least_share)
        for k, point in enumerate(grid):
            model = _learn(known, tally, share, strength, *point, least_share)
            p = np.clip([model.score(ws) for ws, _ in asked], 1e-9, 1 - 1e-9)
            lost[k] -= float((wt * np.where(y == 1, np.log(p), np.log(1 - p))).sum())
    return _learn(texts, _tally(texts), share, strength, *grid[lost.index(min(lost))], least_share)


def _label_weights(y: np.ndarray, share: float, least_share: float) -> np.ndarray:
    # Missing a toxic text costs more than a second look at a clean one: toxic rows weigh at least ``least_share``.
    share = max(share, least_share)
    return np.where(y == 1, share / max(1, y.sum()), (1 - share) / max(1, (1 - y).sum()))


def _learn(texts: list[tuple[list[bytes], int]], tally: tuple[list[Counter], list[Counter]], share: float, strength: float, least_g: float, least_texts: int, least_share: float) -> ToxicModel:
    model = ToxicModel()
    model.prior = None
    counts, spread = tally
    n0, n1 = sum(counts[0].values()), sum(counts[1].values())
    both = n0 + n1
    docs1 = sum(y for _, y in texts)
    for w in set(counts[0]) | set(counts[1]):
        c0, c1 = counts[0][w], counts[1][w]
        prior = strength * (c0 + c1) / both
        odds = lambda c, n: math.log((c + prior) / (n + strength - c - prior))
        delta = odds(c1, n1) - odds(c0, n0)
        # Signed root of the likelihood ratio: unlike the variance of the log-odds it holds for words that one side lacks.
        want1, want0 = (c0 + c1) * n1 / both, (c0 + c1) * n0 / both
        g = math.sqrt(max(0.0, 2 * ((c1 * math.log(c1 / want1) if c1 else 0.0) + (c0 * math.log(c0 / want0) if c0 else 0.0))))
        # A word of one or two toxic texts says more of their subject than of their tone.
        if g >= least_g and (delta < 0 or (delta >= math.log(2) and spread[1][w] >= max(least_texts, 0.005 * docs1))):
            model.weights[w] = delta
    weights = model.weights
    base = Counter()
    for w, c in counts[0].items():
        if w in weights:
            base[weights[w]] += c
    seen = sum(base.values())
    known = sum(s * c for s, c in base.items())
    # The background must drift down, or chance segments would grow without bound.
    model.drift = min(-0.02, -(known + 0.05 * n0) / max(1, n0 - seen))
    steps = [(s, c / n0) for s, c in base.items()] + [(model.drift, (n0 - seen) / n0)]
    if any(s > 0 for s, _ in steps):
        lo, hi = 1e-6, 1.0
        value = lambda x: sum(p * math.exp(min(700.0, x * s)) for s, p in steps) - 1
        while value(hi) < 0 and hi < 64:
            hi *= 2
        for _ in range(60):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if value(mid) < 0 else (lo, mid)
        model.decay = max(lo, 1e-3)
    tops = [(len(ws), max((s for s, _, _ in maximal_segments(model.steps(ws))), default=0.0)) for ws, y in texts if y == 0 and ws]
    # Moment fit of the scale: the mean of decay * best - log(length) is log(scale) plus Euler's constant.
    mean = np.mean([model.decay * s - math.log(n) for n, s in tops]) if tops else 0.0
    model.scale = math.exp(min(0.0, mean - 0.5772156649))
    x = np.array([math.log1p(model.evidence(ws)[0]) for ws, _ in texts])
    y = np.array([y for _, y in texts], float)
    wt = _label_weights(y, share, least_share)
    cost = lambda a, b: float((wt * (np.logaddexp(0, a * x + b) - y * (a * x + b))).sum()) + 5e-6 * a * a + 5e-9 * b * b
    a, b = 0.0, 0.0
    now = cost(a, b)
    for _ in range(200):
        p = 1 / (1 + np.exp(-np.clip(a * x + b, -60, 60)))
        g = np.array([(wt * (p - y) * x).sum() + 1e-5 * a, (wt * (p - y)).sum() + 1e-8 * b])
        q = wt * p * (1 - p) + 1e-12
        h = np.array([[(q * x * x).sum() + 1e-5, (q * x).sum()], [(q * x).sum(), q.sum() + 1e-8]])
        step = np.linalg.solve(h, g)
        # A whole Newton step can overshoot where labels nearly part; the curve is convex, so a shorter one always lowers it.
        while (then := cost(a - step[0], b - step[1])) > now and np.abs(step).max() > 1e-9:
            step = step / 2
        if then >= now - 1e-13:
            break
        a, b, now = a - step[0], b - step[1], then
    model.a, model.b = max(0.0, float(a)), float(b)
    return model


def fit(docs: DataFrame, labels: DataFrame, *, bound: int = 6000, longest: int = 1 << 16) -> ToxicModel:
    """Train on about ``bound`` labelled rows at most, half of each kind, of texts up to ``longest`` bytes."""
    known = labels.where("toxic in (0, 1) and doc_id is not null").select("doc_id", F.col("toxic").cast("int").alias("y")).distinct()
    counts = {r.y: r.n for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    chosen = sample(known, "y", bound, "tox")
    texts = docs.where(F.col("text").isNotNull() & (F.octet_length("text") <= longest)).select("doc_id", "text")
    rows = texts.join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "y").collect()
    rows = sorted(rows, key=lambda r: (str(r.doc_id), r.y, r.text))
    total = sum(counts.values())
    return train([(r.text, r.y) for r in rows], counts.get(1, 0) / total if total else 0.0)


def score(docs: DataFrame, model: ToxicModel, *, text: str = "text", carry: tuple[str, ...] = ("doc_id",), threshold: float = 0.7, spans: bool = False) -> DataFrame:
    """``carry`` columns with score and predicted; with ``spans`` also the significant segments as word places."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(*carry, F.col(text).alias("_text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name != "_text")

    def step(batches):
        model = held.value
        for batch in batches:
            names = [n for n in batch.schema.names if n != "_text"]
            out, marks = [], []
            for t in batch.column(batch.schema.get_field_index("_text")).to_pylist():
                ws = text_words(t)
                out.append(model.score(ws))
                if spans:
                    marks.append([{"first": a, "last": b, "score": s} for s, a, b in model.evidence(ws)[1]])
            cols = [batch.column(n) for n in names] + [pa.array(out, pa.float64()), pa.array([int(s >= threshold) for s in out], pa.int32())]
            if spans:
                cols.append(pa.array(marks, pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32()), ("score", pa.float64())]))))
            yield pa.RecordBatch.from_arrays(cols, [*names, "score", "predicted", *["segments"] * spans])

    extra = ", segments array<struct<first:int,last:int,score:double>>" if spans else ""
    return rows.mapInArrow(step, f"{schema}, score double, predicted int{extra}")
